"""Engines that answer workloads of metapath queries: the reference method and those it is compared with.

All engines give the same (src, dst, n) for a query; they differ in the order of products and in what
they keep. The reference engine plans each query with what is stored, keeps counts of overlaps, stores
the whole result and the longest computed overlap, and replaces by utility with dependencies.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field
from functools import reduce
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathloom.plans.cost import ENTRY_BYTES, MatrixStats, uniform_operations
from pathloom.plans.overlap import SubpathIndex, prefixes
from pathloom.plans.planner import ChainPlanner, Known, Plan
from pathloom.plans.policies import MOST_SHARE, LruPolicy, SizeCostPolicy, dependency_policy
from pathloom.plans.query import PathQuery
from pathloom.sources.networks import TypedNetwork
from pathloom.sources.storage import METRICS_SCHEMA, shuffles_dropped

from .backends import EstimateBackend, TableBackend, operand, operand_stats
from .matrix import dense_multiply, dense_rows, dense_tiles, diagonal, multiply, restrict, sparse_rows, squared, summary
from .tiles import dealt_by_entries, squared_by_tiles, squared_summary

#: Largest number of cells of a matrix that the dense baseline holds as rows; larger ones are multiplied in tiles.
MOST_CELLS = 4_000_000
#: Share of a type's nodes up to which those that a selection is expected to reach cut a later step.
FEW_REACHED = 1 / 8


def lower(net: TypedNetwork, q: PathQuery, plan: Plan, have: dict[tuple[int, int], Any] | None = None, decimal: bool = False, backend=None):
    """A plan as one lazy matrix; spans in have are read instead of computed."""
    backend = backend or TableBackend(net, decimal)
    if have and (plan.i, plan.j) in have:
        return have[plan.i, plan.j]
    if plan.split is None:
        return backend.operand(q, plan.i)
    x, y = (lower(net, q, p, have, decimal, backend) for p in plan.parts)
    return backend.multiply(x, y, plan)


def palindromic(q: PathQuery) -> bool:
    """Does a path read the same from both ends, constraints too."""
    last = len(q) - 1
    return q.types == q.types[::-1] and q.reversible(0, last) and last % 2 == 0 and q.reversed_span(0, last)[1] == q.key(0, last)


def evaluate(net: TypedNetwork, q: PathQuery, planner: ChainPlanner | None = None, decimal: bool = False) -> DataFrame:
    """(src, dst, n): all pairs of end nodes with the number of matching paths.

    Where a palindromic path's best plan meets in its middle, one half is computed and multiplied with its own transpose.
    Of orders that do not look at selections, products that a selection reaches later are cut to what it reaches.
    """
    planner = planner or ChainPlanner()
    stats = operand_stats(net, q)
    plan = planner.plan(stats)
    if meets_in_its_middle(q, plan):
        x, left, operations = half_of(net, q, plan, decimal)
        if not decimal and dealt_by_entries(operations, left.nnz):
            return squared_by_tiles(x, operations, left.nnz)
        return squared(x, decimal, operations, left.cols)
    return lower(net, q, plan, cut(net, q, plan, stats) if planner.kind != "sparse" else None, decimal)


def cut(net: TypedNetwork, q: PathQuery, plan: Plan, stats: list[MatrixStats]) -> dict[tuple[int, int], DataFrame]:
    """The first steps of products on a plan's right sides, restricted to the nodes that selections before them reach, where few are expected."""
    firsts = {p.parts[1].i for p in plan.products() if p.parts[1].split is not None}
    out: dict[tuple[int, int], DataFrame] = {}
    keys, reached = None, 0.0
    for step in range(max(firsts, default=-1) + 1):
        x, nnz, size = operand(net, q, step), stats[step].nnz, net.size(q.types[step])
        if keys is not None and reached <= FEW_REACHED * size:
            x, nnz = restrict(x, keys, "src"), nnz * reached / max(1, size)
            if step in firsts:
                out[step, step + 1] = x
        elif not q.at(step):
            keys = None
            continue
        keys, reached = x.select(F.col("dst").alias("id")).distinct(), nnz
    return out


def evaluate_summary(net: TypedNetwork, q: PathQuery) -> DataFrame:
    """n_pairs, sum_n, max_n of a query's result. Pairs of a large palindromic one are summed up where they are made."""
    plan = ChainPlanner().plan(operand_stats(net, q))
    if meets_in_its_middle(q, plan):
        x, left, operations = half_of(net, q, plan)
        if dealt_by_entries(operations, left.nnz):
            return squared_summary(x, operations, left.nnz)
    return summary(evaluate(net, q))


def meets_in_its_middle(q: PathQuery, plan: Plan) -> bool:
    return plan.split is not None and 2 * plan.split == len(q) - 1 and palindromic(q)


def half_of(net: TypedNetwork, q: PathQuery, plan: Plan, decimal: bool = False) -> tuple[DataFrame, MatrixStats, float]:
    """The first half of a palindromic path, its expected size, and the scalar products with its transpose."""
    # the middle's predicates are folded into the second half's source, so they are set on the first half's end
    half = PathQuery(q.types[: plan.split + 1], q.edges[: plan.split], q.key(0, plan.split))
    left = plan.parts[0].stats
    return lower(net, half, plan.parts[0], decimal=decimal), left, uniform_operations(left, plan.parts[1].stats)


# selections as operands of their own


def chain(net: TypedNetwork, q: PathQuery) -> tuple[list[tuple[str, int]], list[MatrixStats]]:
    """A query's steps and selections in order, with their sizes: the planner may put a selection to either side."""
    items, stats = [], []
    for p in range(len(q)):
        if q.at(p):
            n = net.size(q.types[p])
            items.append(("select", p))
            stats.append(MatrixStats(n, n, n * reduce(lambda a, c, t=q.types[p]: a * net.share(t, c), q.at(p), 1.0)))
        if p < len(q) - 1:
            items.append(("step", p))
            stats.append(net.step_stats(q.types[p], q.types[p + 1], q.edges[p]))
    return items, stats


def evaluate_operands(net: TypedNetwork, q: PathQuery, planner: ChainPlanner | None = None) -> DataFrame:
    """As evaluate, with selections as diagonal operands that the planner places; a product with one is a semi join."""
    items, stats = chain(net, q)

    def made(plan: Plan) -> tuple[str, DataFrame]:
        if plan.split is None:
            kind, p = items[plan.i]
            if kind == "step":
                return kind, operand(net, q, p, folded=False)
            keys = reduce(lambda a, c: a.join(net.selection(q.types[p], c), "id", "left_semi"), q.at(p)[1:], net.selection(q.types[p], q.at(p)[0]))
            return kind, keys
        (kx, x), (ky, y) = map(made, plan.parts)
        if kx == "select" and ky == "select":
            return "select", x.join(y, "id", "left_semi")
        if kx == "select":
            return "step", restrict(y, x, "src")
        if ky == "select":
            return "step", restrict(x, y, "dst")
        return "step", multiply(x, y)

    kind, x = made((planner or ChainPlanner()).plan(stats))
    return x if kind == "step" else diagonal(x)


# traversals


def instances(net: TypedNetwork, q: PathQuery) -> DataFrame:
    """One row per matching path: src, dst, the nodes v0, v1, ... and the product of edge weights."""
    rows = None
    for step in range(len(q) - 1):
        x = operand(net, q, step)
        named = x.select(F.col("src").alias(f"v{step}"), F.col("dst").alias(f"v{step + 1}"), F.col("n").alias(f"w{step}"))
        rows = named if rows is None else rows.join(named, f"v{step}")
    nodes = [f"v{i}" for i in range(len(q))]
    weight = reduce(lambda a, b: a * b, (F.col(f"w{i}") for i in range(len(q) - 1)))
    return rows.select(*nodes, weight.alias("weight"), F.col("v0").alias("src"), F.col(nodes[-1]).alias("dst"))


@dataclass
class TraversalEngine:
    """Each query as one declarative statement: all steps joined, paths counted at the end.

    Steps are temporary views. A statement's text depends on the path and on which positions have predicates;
    it is made once, and keys reach it as named parameters.
    """

    net: TypedNetwork
    statements: dict[tuple, str] = field(default_factory=dict)
    reused: int = 0
    views: dict[tuple, str] = field(default_factory=dict)

    def _view(self, src: str, dst: str, edge: str | None) -> str:
        if (src, dst, edge) not in self.views:
            name = f"step_{self.net.name}_{id(self)}_{len(self.views)}"
            self.net.adjacency(src, dst, edge).createOrReplaceTempView(name)
            self.views[src, dst, edge] = name
        return self.views[src, dst, edge]

    def _nodes(self, t: str) -> str:
        if (t,) not in self.views:
            self.views[(t,)] = f"nodes_{self.net.name}_{id(self)}_{len(self.views)}"
            self.net.nodes[t].df.createOrReplaceTempView(self.views[(t,)])
        return self.views[(t,)]

    def run_one(self, q: PathQuery) -> DataFrame:
        last = len(q) - 2
        values, where, shape = {}, [], []
        for i, (p, predicate) in enumerate(q.constraints):
            text = self.net.expanded(q.types[p], predicate)
            column = f"e{p}.src" if p <= last else f"e{last}.dst"
            if text.startswith("id = "):
                values[f"key{i}"] = int(text[5:])
                where.append(f"{column} = :key{i}")
            else:
                where.append(f"{column} IN (SELECT id FROM {self._nodes(q.types[p])} WHERE {text})")
            shape.append(where[-1])
        template = (q.symbols, tuple(shape))
        if template in self.statements:
            self.reused += 1
        else:
            steps = [f"{self._view(q.types[i], q.types[i + 1], q.edges[i])} e{i}" for i in range(last + 1)]
            on = [f"e{i}.dst = e{i + 1}.src" for i in range(last)] + where
            weight = " * ".join(f"e{i}.n" for i in range(last + 1))
            condition = f" WHERE {' AND '.join(on)}" if on else ""
            self.statements[template] = f"SELECT e0.src AS src, e{last}.dst AS dst, CAST(SUM({weight}) AS BIGINT) AS n FROM {', '.join(steps)}{condition} GROUP BY e0.src, e{last}.dst"
        return self.net.spark.sql(self.statements[template], args=values)

    def close(self) -> None:
        for name in self.views.values():
            self.net.spark.catalog.dropTempView(name)


def traversal(net: TypedNetwork, q: PathQuery) -> DataFrame:
    """What a declarative path query does."""
    return TraversalEngine(net).run_one(q)


def tiles(net: TypedNetwork, q: PathQuery, plan: Plan) -> DataFrame:
    """A plan whose products are those of dense tiles."""
    if plan.split is None:
        return operand(net, q, plan.i)
    (x, y), (a, b) = (tiles(net, q, p) for p in plan.parts), (p.stats for p in plan.parts)
    return dense_tiles(x, y, a.rows, a.cols, b.cols)


def evaluate_dense(net: TypedNetwork, q: PathQuery, most: int = MOST_CELLS) -> DataFrame:
    """The dense baseline: zeros included, ordered by dimensions only. In full rows up to ``most`` cells of any matrix it makes, else in tiles."""
    stats = operand_stats(net, q)
    plan = ChainPlanner("dense").plan(stats)
    if max(s.rows * s.cols for s in [*stats, *(p.stats for p in plan.products())]) > most:
        return tiles(net, q, plan)
    node = lambda p: net.nodes[q.types[p]].df.select("id")

    def rows(p: Plan) -> DataFrame:
        if p.split is None:
            return dense_rows(operand(net, q, p.i), node(p.j), node(p.i))
        x, y = map(rows, p.parts)
        return dense_multiply(x, node(p.split), y)

    return sparse_rows(rows(plan), node(plan.j))


# workloads


@dataclass
class QueryMetrics:
    engine: str
    pos: int
    path: str
    plan_seconds: float = 0.0
    exec_seconds: float = 0.0
    products: int = 0
    cached_spans: int = 0
    offers: int = 0
    evictions: int = 0
    rejected: int = 0
    whole_hits: int = 0
    keyed_hits: int = 0
    resident_bytes: float = 0.0
    cost: float = 0.0
    operations: int = 0


@dataclass
class WorkloadEngine:
    """Answers queries one after the other.

    admission: none, final (whole results), all (every product) or overlap (the whole result and the longest
    computed span that the index has at an internal node). policy: lru, size_cost or dependency.
    substitute: none, cached, or cached+evicted, what the planner is told of earlier results.
    freq_scope: a span's frequency by its constraints, or by its pattern alone; without constraint_aware the
    index does not keep the former. cost_measure: estimated, or measured seconds (the planner's
    coefficients should then be fitted to seconds). ancestors, nearest: which entries count as made from which
    (the tree sees prefixes). horizon: queries after which the index forgets one.
    Results are kept by the backend, as tables in the shared folder unless another is given; size is entries
    times ENTRY_BYTES. With reuse_reverse, a stored result also serves the reversed path; with
    reuse_subsumed, one without constraints serves a span with constraints at its ends. With
    second_level, evicted results stay and are read again when wanted; else they are deleted when the
    next query but one starts, so a lazy result is good until then.
    """

    net: Any
    admission: str = "overlap"
    policy: str = "dependency"
    capacity: float = 64 << 20
    planner: ChainPlanner = field(default_factory=ChainPlanner)
    substitute: str = "cached+evicted"
    min_freq: int = 2
    name: str = "reference"
    reuse_reverse: bool = False
    reuse_subsumed: bool = False
    second_level: bool = False
    constraint_aware: bool = True
    freq_scope: str = "constraint"
    cost_measure: str = "estimated"
    cache_restricted: bool = False
    ancestors: Callable = prefixes
    nearest: bool = False
    horizon: int | None = None
    backend: Any = None
    clock: Callable[[], float] = time.perf_counter

    def __post_init__(self):
        self.index = SubpathIndex(self.constraint_aware, self.horizon)
        if self.policy == "lru":
            self.cache = LruPolicy(self.capacity, MOST_SHARE)
        elif self.policy == "size_cost":
            self.cache = SizeCostPolicy(self.capacity, MOST_SHARE, frequency=self._frequency)
        else:
            self.cache = dependency_policy(self.capacity, self.ancestors, MOST_SHARE, frequency=self._frequency, nearest=self.nearest)
        self.backend = self.backend or TableBackend(self.net, both=True)
        self.tables: dict[tuple, Any] = {}
        self.demoted: dict[tuple, Any] = {}
        self.going: list[list] = [[], []]  # matrices no longer stored, by the query that dropped them
        self.metrics: list[QueryMetrics] = []

    def _frequency(self, key: tuple) -> int:
        span, constraints = key
        return self.index.frequency(span, constraints if self.freq_scope == "constraint" else None)

    # what is known of a query's spans

    def _known(self, q: PathQuery) -> tuple[dict[tuple[int, int], Known], dict[tuple[int, int], tuple]]:
        """What the planner may use for each span, and how spans that are stored are read."""
        out, how = {}, {}
        if self.admission == "none" or self.substitute == "none":
            return out, how
        for i in range(len(q) - 1):
            for j in range(i + 2 - self.cache_restricted, len(q)):
                if self.admission == "final" and (i, j) != (0, len(q) - 1):
                    continue
                found = self._source(q, i, j)
                if found:
                    nnz, kind, key = found
                    if kind == "evicted":
                        out[i, j] = Known(nnz, self.index.records[key].cost, False)
                    else:
                        out[i, j], how[i, j] = Known(nnz, 0.0, True), (kind, key)
        return out, how

    def _source(self, q: PathQuery, i: int, j: int) -> tuple[float, str, tuple] | None:
        """Where a span's result comes from: (entries, kind, key)."""
        key = (q.span(i, j), q.key(i, j))
        record = self.index.record(*key)
        if record and record.stored:
            return record.nnz, "stored", key
        if key in self.demoted:
            return record.nnz if record else 0.0, "demoted", key
        if self.reuse_reverse and q.reversible(i, j):
            back = q.reversed_span(i, j)
            if back in self.tables:
                return self.index.records[back].nnz, "reverse", back
        ends = [c for c in key[1] if c[0] in (0, j - i)]
        if self.reuse_subsumed and key[1] and ends == list(key[1]) and (key[0], ()) in self.tables:
            share = reduce(lambda a, c: a * self.net.share(q.types[i + c[0]], c[1]), ends, 1.0)
            return self.index.records[key[0], ()].nnz * share, "subsumed", (key[0], ())
        if record and self.substitute == "cached+evicted":
            return record.nnz, "evicted", key
        return None

    def _read(self, q: PathQuery, i: int, j: int, kind: str, key: tuple) -> Any:
        if kind == "demoted":
            return self.demoted[key]
        self.cache.touch(key)
        x = self.tables[key]
        if kind == "reverse":
            return self.backend.transposed(x)
        if kind == "subsumed":
            for p, predicate in q.key(i, j):
                x = self.backend.limited(x, q.types[i + p], predicate, "src" if p == 0 else "dst")
        return x

    # what is kept

    def _offers(self, q: PathQuery, plan: Plan) -> list[Plan]:
        """Computed spans to store, in order; the whole result last."""
        made = list(plan.products())
        if self.admission == "none" or not made:
            return []
        if self.admission == "all":
            return made
        whole = made[-1:]
        if self.admission == "final":
            return whole
        if self.cache_restricted:
            made = [p for p in _spans(plan) if p.split is None and not p.cached and q.key(p.i, p.j)] + made
        seen = [p for p in made[:-1] if self._frequency((q.span(p.i, p.j), q.key(p.i, p.j))) >= self.min_freq]
        longest = sorted(seen, key=lambda p: (p.i - p.j, p.i))[:1]
        return longest + whole

    def _full_cost(self, q: PathQuery, stats: list[MatrixStats], p: Plan) -> float:
        """What a span costs with nothing stored."""
        return self.planner.plan(stats[p.i : p.j]).cost

    def _retire(self, x: Any) -> None:
        self.going[-1].append(x)

    def run_one(self, q: PathQuery, pos: int = 0) -> Any:
        """The query's result: a lazy DataFrame over what is stored, or the backend's matrix."""
        for x in self.going.pop(0):
            self.backend.drop(x)
        self.going.append([])
        m = QueryMetrics(self.name, pos, q.path)
        t = self.clock()
        self.index.insert(q)
        stats = operand_stats(self.net, q, both=True)
        known, how = self._known(q)
        plan = self.planner.plan(stats, known)
        m.plan_seconds = self.clock() - t
        t = self.clock()
        have: dict[tuple[int, int], Any] = {}
        for p in _spans(plan):
            if p.cached:
                kind, key = how[p.i, p.j]
                have[p.i, p.j] = self._read(q, p.i, p.j, kind, key)
                m.cached_spans += 1
                m.whole_hits += p is plan
                m.keyed_hits += bool(q.key(p.i, p.j))
        made = list(plan.products())
        m.products = len(made)
        m.cost = float(sum(self.planner.step_cost(*(x.stats for x in p.parts), p.stats) for p in made))
        kept_cost: dict[tuple[int, int], float] = {}  # of this query's spans that were stored just now
        for p in self._offers(q, plan):
            self._offer(q, p, stats, have, kept_cost, m)
        result = lower(self.net, q, plan, have, backend=self.backend)
        m.exec_seconds = self.clock() - t
        m.operations = self.backend.operations()
        m.resident_bytes = float(self.cache.used)
        self.metrics.append(m)
        return result

    def _offer(self, q: PathQuery, p: Plan, stats: list[MatrixStats], have: dict, kept_cost: dict, m: QueryMetrics) -> None:
        """Compute a span, keep it if the policy takes it, and note what is known of it."""
        key = (q.span(p.i, p.j), q.key(p.i, p.j))
        t = self.clock()
        made, nnz = self.backend.keep(lower(self.net, q, p, have, backend=self.backend), p)
        seconds = self.clock() - t
        have[p.i, p.j] = made
        inside = [c for (i, j), c in kept_cost.items() if p.i <= i and j <= p.j]
        if self.cost_measure == "measured":
            residual = seconds
            full = seconds + sum(self._recorded(q, s) for s in _spans(p) if s.cached) + sum(inside)
        else:
            full = self._full_cost(q, stats, p)
            residual = max(p.cost - sum(inside), 0.0)
        outcome = self.cache.request(key, residual if self.policy == "dependency" else full, nnz * ENTRY_BYTES, full)
        m.offers += 1
        m.evictions += len(outcome.evicted)
        for old in outcome.evicted:
            self.index.note(*old, stored=False)
            if self.second_level:
                self.demoted[old] = self.tables.pop(old)
            else:
                self._retire(self.tables.pop(old))
        self.index.note(*key, cost=full, residual=residual, nnz=float(nnz), stored=outcome.stored)
        if outcome.stored:
            self.tables[key] = made
            kept_cost[p.i, p.j] = residual
            if key in self.demoted:
                self._retire(self.demoted.pop(key))
        else:
            m.rejected += 1
            self._retire(made)

    def _recorded(self, q: PathQuery, s: Plan) -> float:
        record = self.index.record(q.span(s.i, s.j), q.key(s.i, s.j))
        return record.cost if record else 0.0

    def summary_of(self, q: PathQuery, pos: int) -> tuple[int, int, int]:
        """n_pairs, sum_n, max_n of a query's result, with its time and scalar products in the metrics."""
        t = self.clock()
        found = self.backend.summary(self.run_one(q, pos))
        self.metrics[-1].exec_seconds = self.clock() - t - self.metrics[-1].plan_seconds
        return found

    def run(self, queries: Iterable[PathQuery]) -> DataFrame:
        """pos, n_pairs, sum_n, max_n of each query, in order."""
        rows = [(pos, *self.summary_of(q, pos)) for pos, q in enumerate(queries)]
        return self.net.spark.createDataFrame(rows, "pos int, n_pairs long, sum_n long, max_n long")

    def invalidate(self, edge_name: str, net: TypedNetwork) -> list[tuple]:
        """Go on with a network in which a relation has changed: results that used it are dropped. Gives their keys."""
        ends = next({(e.src, e.dst), (e.dst, e.src)} for e in net.edges if e.name == edge_name)
        named = edge_name if edge_name.startswith("next") else None
        stale = []
        for key in [*self.tables, *self.demoted]:
            span = key[0]
            for a, b in zip(span, span[1:], strict=False):
                relation = b[1 : b.index("]")] if b.startswith("[") else None
                if relation == named and (a.rpartition("]")[2], b.rpartition("]")[2]) in ends:
                    stale.append(key)
                    break
        for key in stale:
            self._retire(self.tables.pop(key) if key in self.tables else self.demoted.pop(key))
            if key in self.cache:
                self.cache.forget(key)
        for record in [r for k, r in self.index.records.items() if k in set(stale)]:
            record.stored = False
        self.net = net
        self.backend.net = net
        return stale

    def catalog(self) -> DataFrame:
        """sub_path, constraints, nnz, cost, state of the spans that are or were stored."""
        from pathloom.plans.query import key_text

        state = lambda k: "stored" if k in self.tables else "demoted" if k in self.demoted else "evicted"
        rows = [("-".join(s), key_text(c), float(r.nnz), float(r.cost), state((s, c))) for (s, c), r in self.index.records.items()]
        return self.net.spark.createDataFrame(rows, "sub_path string, constraints string, nnz double, cost double, state string")

    def metrics_df(self) -> DataFrame:
        return self.net.spark.createDataFrame([tuple(vars(m).values()) for m in self.metrics], METRICS_SCHEMA)


def _spans(plan: Plan) -> Iterable[Plan]:
    yield plan
    for p in plan.parts:
        yield from _spans(p)


#: Engines by name: how they admit and replace.
CACHES = {
    "sparse": ("none", "lru"),
    "final_cache": ("final", "lru"),
    "all_products": ("all", "lru"),
    "tree_lru": ("overlap", "lru"),
    "tree_size_cost": ("overlap", "size_cost"),
    "reference": ("overlap", "dependency"),
}


def engine(net, name: str, capacity: float = 64 << 20, **options) -> WorkloadEngine:
    admission, policy = CACHES[name]
    substitute = "cached" if name in ("final_cache", "all_products") else "cached+evicted"
    return WorkloadEngine(net, admission, policy, capacity, **{"substitute": substitute, "name": name, **options})


def simulated(net, queries: list[PathQuery], name: str, capacity: float, **options) -> list[QueryMetrics]:
    """What an engine would do over a workload, with estimates in place of results."""
    e = engine(net, name, capacity, backend=EstimateBackend(), **options)
    for i, q in enumerate(queries):
        e.run_one(q, i)
    return e.metrics


def run_uncached(net: TypedNetwork, queries: list[PathQuery], kind: str) -> DataFrame:
    """pos, n_pairs, sum_n, max_n of queries without a cache: kind is sparse, left, right, dense-order or traversal.

    One job answers all, but for the dense order, whose products are large: there each query is a job whose shuffled files go before the next.
    """
    parts, walker = [], TraversalEngine(net)
    for pos, q in enumerate(queries):
        result = walker.run_one(q) if kind == "traversal" else evaluate(net, q, ChainPlanner(kind))
        found = summary(result).select(F.lit(pos).alias("pos"), "n_pairs", "sum_n", "max_n")
        if kind == "dense":
            with shuffles_dropped(net.spark):
                found = net.spark.createDataFrame([tuple(found.first())], found.schema)  # one row
        parts.append(found)
    return reduce(DataFrame.unionByName, parts)
