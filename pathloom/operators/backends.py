"""Where an engine's matrices live: tables that Spark computes, or nowhere, with estimates in place of results."""

from __future__ import annotations

import time
from collections import OrderedDict
from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from pathloom.plans.cost import ENTRY_BYTES, MatrixStats, uniform_operations
from pathloom.plans.planner import Plan
from pathloom.plans.query import PathQuery
from pathloom.sources.networks import TypedNetwork
from pathloom.sources.storage import dropped, shuffles_dropped, stored, stored_counted

from .matrix import multiply, restrict, summary, transposed

#: Bytes of a product's expected entries beyond which engines that share it do not store it unless another is made of it.
LARGE_BYTES = 128 << 20


def limited(net: TypedNetwork, x: DataFrame, node_type: str, predicate: str, side: str) -> DataFrame:
    """The entries whose node at a side satisfies a predicate: a filter if it names a key, which reaches the scan, else a semi join."""
    text = net.expanded(node_type, predicate)
    if text.startswith("id = "):
        return x.filter(F.expr(f"{side}{text[2:]}"))
    return restrict(x, net.selection(node_type, predicate), side)


def folded_at(net, q: PathQuery, step: int, both: bool) -> list[tuple[str, int, str]]:
    """(side, position, predicate) that are folded into a step's matrix.

    All at its source; at its end those of the last step, and equalities on a key, which cost no join and leave
    less to multiply. With both, all at its end too: so a span's result has what its own predicates say, whatever
    query it is read for. Predicates that two steps share are applied twice, which changes nothing.
    """
    out = [("src", step, c) for c in q.at(step)]
    last = both or step + 2 == len(q)
    return out + [("dst", step + 1, c) for c in q.at(step + 1) if last or net.expanded(q.types[step + 1], c).startswith("id = ")]


def operand(net: TypedNetwork, q: PathQuery, step: int, folded: bool = True, both: bool = False) -> DataFrame:
    """A step's matrix, with predicates folded in."""
    x = net.adjacency(q.types[step], q.types[step + 1], q.edges[step])
    for side, position, predicate in folded_at(net, q, step, both) if folded else ():
        x = limited(net, x, q.types[position], predicate, side)
    return x.select("src", "dst", "n")


def operand_stats(net, q: PathQuery, both: bool = False) -> list[MatrixStats]:
    """Sizes of a query's steps; a predicate takes its share of the rows or columns it is folded into."""
    out = []
    for step in range(len(q) - 1):
        share = reduce(lambda a, f: a * net.share(q.types[f[1]], f[2]), folded_at(net, q, step, both), 1.0)
        out.append(net.step_stats(q.types[step], q.types[step + 1], q.edges[step]).reduced(share))
    return out


class TableBackend:
    """Matrices as lazy DataFrames; what is kept is a table in the shared folder."""

    def __init__(self, net: TypedNetwork, decimal: bool = False, both: bool = False):
        self.net, self.decimal, self.both = net, decimal, both

    def operand(self, q: PathQuery, step: int) -> DataFrame:
        return operand(self.net, q, step, both=self.both)

    def multiply(self, x: DataFrame, y: DataFrame, plan: Plan) -> DataFrame:
        left, right = (p.stats for p in plan.parts)
        return multiply(x, y, decimal=self.decimal, operations=uniform_operations(left, right), middle=left.cols)

    def transposed(self, x: DataFrame) -> DataFrame:
        return transposed(x)

    def limited(self, x: DataFrame, node_type: str, predicate: str, side: str) -> DataFrame:
        return limited(self.net, x, node_type, predicate, side)

    def keep(self, x: DataFrame, plan: Plan) -> tuple[DataFrame, float]:
        return stored_counted(x, "span")

    def drop(self, x: DataFrame) -> None:
        dropped(x)

    def summary(self, x: DataFrame) -> tuple[int, int, int]:
        return tuple(summary(x).first())  # one row

    def operations(self) -> int:
        return 0


@dataclass(eq=False)
class Kept:
    """A product that is made when it is asked for: its table, if there is one, its entries' count, sum and maximum, and the seconds they took."""

    of: tuple
    make: Callable[[], DataFrame]
    table: DataFrame | None = None
    sums: tuple[int, int, int] | None = None
    seconds: float = 0.0
    #: Engines that store it, and whether it is found when it is asked for again.
    users: int = 0
    known: bool = True


class SharedTables:
    """Operands and products that several engines make of the same queries over tables: each is made and timed once.

    An engine that makes one again is charged the seconds that it took, by ``clock``. Large products are counted and summed up, and are only
    stored if another is made of them. Between queries, trim lets the least recently used go beyond ``most`` bytes of entries; their tables
    are deleted when no engine stores them.
    """

    def __init__(self, most: float = 2 << 30):
        self.most, self.bytes, self.charged = most, 0.0, 0.0
        self.operands: dict[tuple, DataFrame] = {}
        self.known: OrderedDict[tuple, Kept] = OrderedDict()
        self.stored: set[Kept] = set()

    def clock(self) -> float:
        return time.perf_counter() + self.charged

    def made(self, of: tuple, make: Callable[[], DataFrame], large: bool = False) -> Kept:
        """The product of two matrices, at once as a table unless it is large."""
        key = tuple(map(id, of))  # of is held with the product, so the two stay themselves
        if key in self.known:
            self.known.move_to_end(key)
            self.charged += self.known[key].seconds
            return self.known[key]
        found = self.known[key] = Kept(of, make)
        if not large:
            self.table(found)
        return found

    def table(self, x: Kept) -> DataFrame:
        """A product's table, which is summed up while it is written."""
        if x.table is None:
            frame, sums = x.make(), Observation()
            t = time.perf_counter()
            with shuffles_dropped(frame.sparkSession):
                observed = (F.count(F.lit(1)).alias("pairs"), F.coalesce(F.sum("n"), F.lit(0)).alias("total"), F.coalesce(F.max("n"), F.lit(0)).alias("most"))
                x.table = stored(frame.observe(sums, *observed), "product")
            x.sums = tuple(sums.get[k] for k in ("pairs", "total", "most"))
            x.seconds += time.perf_counter() - t
            self.stored.add(x)
            self.bytes += x.known * x.sums[0] * ENTRY_BYTES
        return x.table

    def sums(self, x: Kept) -> tuple[int, int, int]:
        if x.sums is None:
            frame = x.make()
            t = time.perf_counter()
            with shuffles_dropped(frame.sparkSession):
                x.sums = tuple(summary(frame).first())  # one row
            x.seconds += time.perf_counter() - t
        return x.sums

    def trim(self) -> None:
        while self.bytes > self.most and self.known:
            old = self.known.popitem(last=False)[1]
            old.known = False
            self.bytes -= old.sums[0] * ENTRY_BYTES if old.table else 0
            self.freed(old)

    def freed(self, x: Kept) -> None:
        """Delete a table that is neither known nor stored by an engine; it is made again if a product of it still needs it."""
        if x in self.stored and not x.known and not x.users:
            self.stored.remove(x)
            dropped(x.table)
            x.table = None

    def close(self) -> None:
        for x in self.stored:
            dropped(x.table)
        self.stored.clear()
        self.known.clear()


class SharedTableBackend(TableBackend):
    """Matrices as tables that are shared with other engines: a product is made once for all."""

    def __init__(self, net: TypedNetwork, shared: SharedTables):
        super().__init__(net, both=True)
        self.shared = shared

    def operand(self, q: PathQuery, step: int) -> DataFrame:
        key = (q.types[step], q.types[step + 1], q.edges[step], *((side, predicate) for side, _, predicate in folded_at(self.net, q, step, True)))
        if key not in self.shared.operands:
            self.shared.operands[key] = super().operand(q, step)
        return self.shared.operands[key]

    def multiply(self, x: DataFrame | Kept, y: DataFrame | Kept, plan: Plan) -> Kept:
        make = super().multiply
        return self.shared.made((x, y), lambda: make(self._table(x), self._table(y), plan), plan.stats.bytes > LARGE_BYTES)

    def transposed(self, x: DataFrame | Kept) -> DataFrame:
        return super().transposed(self._table(x))

    def limited(self, x: DataFrame | Kept, node_type: str, predicate: str, side: str) -> DataFrame:
        return super().limited(self._table(x), node_type, predicate, side)

    def keep(self, x: DataFrame | Kept, plan: Plan) -> tuple[Kept, float]:
        x = x if isinstance(x, Kept) else self.shared.made((x,), lambda: x)
        x.users += 1
        return x, self.shared.sums(x)[0]

    def drop(self, x: Kept) -> None:
        x.users -= 1
        self.shared.freed(x)

    def summary(self, x: DataFrame | Kept) -> tuple[int, int, int]:
        return self.shared.sums(x) if isinstance(x, Kept) else super().summary(x)

    def _table(self, x: DataFrame | Kept) -> DataFrame:
        return self.shared.table(x) if isinstance(x, Kept) else x


class EstimateBackend:
    """Nothing is executed: estimates stand for entries and scalar products, so that long workloads can be compared by cost."""

    def __init__(self):
        self.done = 0.0

    def operand(self, q, step):
        return None

    def multiply(self, x, y, plan: Plan):
        self.done += uniform_operations(*(p.stats for p in plan.parts))

    def transposed(self, x):
        return None

    def limited(self, x, node_type, predicate, side):
        return None

    def keep(self, x, plan: Plan):
        return None, plan.stats.nnz

    def drop(self, x):
        pass

    def summary(self, x):
        return 0, 0, 0

    def operations(self) -> int:
        done, self.done = int(self.done), 0.0
        return done
