"""Sparse matrices as DataFrames (src, dst, n), and their products."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathloom.plans.cost import ENTRY_BYTES

#: How two entries combine along a path, and how paths between one pair of nodes do.
SEMIRINGS = {
    "count": (lambda x, y: x * y, F.sum),
    "reach": (lambda x, y: F.least(x, y), F.max),
    "shortest": (lambda x, y: x + y, F.min),
    "bottleneck": (lambda x, y: F.least(x, y), F.max),
}


#: Scalar products that one task of a large product takes on, and the most tasks.
TASK_OPERATIONS, MOST_TASKS = 4_000_000, 20_000
#: Bytes of a matrix's entries up to which it is sent to every executor.
BROADCAST_BYTES = 24 << 20


def multiply(x: DataFrame, y: DataFrame, semiring: str = "count", decimal: bool = False, operations: float = 0.0, middle: int = 0) -> DataFrame:
    """The product of two matrices: one join on the middle node, one aggregation by pair.

    Paths between a pair are summed at once, so later products see pairs, not paths. Partial sums
    are taken before the exchange. With decimal, counts are DECIMAL(38, 0) and cannot overflow a long.
    operations and middle are the expected scalar products and the number of middle nodes: where few bytes
    make many products, tasks are dealt by products, and where middle nodes are fewer than tasks, each is
    spread over a grid of cells.
    """
    times, plus = SEMIRINGS[semiring]
    kind = "decimal(38,0)" if decimal else "long"
    left, right, on = _sides(x, y, operations, middle)
    n = times(F.col("nx").cast(kind), F.col("ny").cast(kind)).cast(kind)
    return left.join(right, on).groupBy("a", "b").agg(plus(n).cast(kind).alias("n")).select(F.col("a").alias("src"), F.col("b").alias("dst"), "n")


def hinted(y: DataFrame, kind: str, entries: float) -> DataFrame:
    """A product's side with a hint of how to join it. One of too many entries to be sent to every executor has none: its join is shuffled."""
    return y if kind == "broadcast" and entries * ENTRY_BYTES > BROADCAST_BYTES else y.hint(kind)


def squared(x: DataFrame, decimal: bool = False, operations: float = 0.0, middle: int = 0) -> DataFrame:
    """x times its own transpose: what a palindromic path's two halves give. Pairs are summed on one side of the diagonal and mirrored."""
    kind = "decimal(38,0)" if decimal else "long"
    left, right, on = _sides(x, transposed(x), operations, middle)
    half = left.join(right, on).filter("a <= b").groupBy("a", "b").agg(F.sum(F.col("nx").cast(kind) * F.col("ny").cast(kind)).cast(kind).alias("n"))
    here, there = F.struct(F.col("a").alias("src"), F.col("b").alias("dst")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst"))
    pairs = half.select(F.explode(F.when(F.col("a") == F.col("b"), F.array(here)).otherwise(F.array(here, there))).alias("p"), "n")
    return pairs.select("p.src", "p.dst", "n")


def _sides(x: DataFrame, y: DataFrame, operations: float, middle: int) -> tuple[DataFrame, DataFrame, list[str]]:
    """Both sides of a product's join, as (a, k, nx) and (k, b, ny), and the columns to join on."""
    left = x.select(F.col("src").alias("a"), F.col("dst").alias("k"), F.col("n").alias("nx"))
    right = y.select(F.col("src").alias("k"), F.col("dst").alias("b"), F.col("n").alias("ny"))
    tasks = min(MOST_TASKS, math.ceil(operations / TASK_OPERATIONS))
    if tasks < 2:
        return left, right, ["k"]
    side = math.ceil(math.sqrt(4 * tasks / middle)) if 0 < middle < 4 * tasks else 1
    on = ["k"]
    if side > 1:
        left, right = by_row(left, F.lit(side)), by_column(right, F.lit(side))
        on = ["k", "i", "j"]
    # by number, so that adaptive execution does not put small inputs of large products into one task
    return left.repartition(4 * tasks, *on), right.repartition(4 * tasks, *on), on


def by_row(left: DataFrame, side: Column) -> DataFrame:
    """Left entries of a middle node's grid of side x side cells (i, j): each goes to all cells of the row that its source picks."""
    return left.withColumn("i", F.pmod(F.xxhash64("a"), side).cast("int")).withColumn("j", F.explode(F.sequence(F.lit(0), side - 1)))


def by_column(right: DataFrame, side: Column) -> DataFrame:
    """Right entries likewise, to all cells of a column; a left and a right entry meet in one cell."""
    return right.withColumn("j", F.pmod(F.xxhash64("b"), side).cast("int")).withColumn("i", F.explode(F.sequence(F.lit(0), side - 1)))


def multiply_skewed(x: DataFrame, y: DataFrame, heavy: int = TASK_OPERATIONS) -> DataFrame:
    """The product where some middle nodes have far more paths than others.

    Both sides' degrees tell how many products each middle node takes; one with more than heavy is spread over
    a grid of cells, the others go to one cell. The table of heavy nodes is a small part of the degrees; it is
    broadcast only if the optimizer finds it small.
    """
    left = x.select(F.col("src").alias("a"), F.col("dst").alias("k"), F.col("n").alias("nx"))
    right = y.select(F.col("src").alias("k"), F.col("dst").alias("b"), F.col("n").alias("ny"))
    degrees = left.groupBy("k").agg(F.count("*").alias("into")).join(right.groupBy("k").agg(F.count("*").alias("outof")), "k")
    hot = degrees.filter(F.col("into") * F.col("outof") > heavy).select("k", F.ceil(F.sqrt(F.col("into") * F.col("outof") / heavy)).cast("int").alias("side"))
    side = F.coalesce("side", F.lit(1))
    left = by_row(left.join(hot, "k", "left"), side).drop("side")
    right = by_column(right.join(hot, "k", "left"), side).drop("side")
    joined = left.join(right, ["k", "i", "j"])
    return joined.groupBy("a", "b").agg(F.sum(F.col("nx") * F.col("ny")).cast("long").alias("n")).select(F.col("a").alias("src"), F.col("b").alias("dst"), "n")


def restrict(x: DataFrame, keys: DataFrame, side: str) -> DataFrame:
    """The entries whose src or dst is among keys (id): the product with a diagonal selection matrix."""
    return x.join(keys.withColumnRenamed("id", side), side, "left_semi").select("src", "dst", "n")


def diagonal(keys: DataFrame) -> DataFrame:
    """Keys (id) as a selection matrix."""
    return keys.select(F.col("id").alias("src"), F.col("id").alias("dst"), F.lit(1).cast("long").alias("n"))


def transposed(x: DataFrame) -> DataFrame:
    return x.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "n")


def added(x: DataFrame, y: DataFrame) -> DataFrame:
    """Entrywise sum; with a product's distributivity, how appended edges reach cached results."""
    return x.unionByName(y).groupBy("src", "dst").agg(F.sum("n").alias("n"))


def operations(x: DataFrame, y: DataFrame) -> DataFrame:
    """n_op: scalar products of x times y, from degrees alone."""
    out = x.groupBy(F.col("dst").alias("k")).agg(F.count("*").alias("into"))
    into = y.groupBy(F.col("src").alias("k")).agg(F.count("*").alias("outof"))
    return out.join(into, "k").agg(F.coalesce(F.sum(F.col("into") * F.col("outof")), F.lit(0)).cast("long").alias("n_op"))


def sketch_entries(x: DataFrame, y: DataFrame) -> DataFrame:
    """sketch_nnz: the product's entries by the count sketch, from degrees alone (see plans.cost.sketch_product)."""
    out = x.groupBy(F.col("dst").alias("k")).agg(F.count("*").alias("into"))
    into = y.groupBy(F.col("src").alias("k")).agg(F.count("*").alias("outof"))
    rows = x.groupBy("src").agg(F.count("*").alias("c")).agg(F.count("*").alias("filled_rows"), F.max("c").alias("most_row"))
    cols = y.groupBy("dst").agg(F.count("*").alias("c")).agg(F.count("*").alias("filled_cols"), F.max("c").alias("most_col"))
    shape = rows.join(cols).withColumn("cells", F.col("filled_rows").cast("double") * F.col("filled_cols"))  # one row each
    met = (F.col("into") * F.col("outof")).cast("double")
    sums = out.join(into, "k").join(F.broadcast(shape)).agg(
        F.sum(met).alias("met"), F.sum(F.log1p(-F.least(met / F.col("cells"), F.lit(1 - 1e-12)))).alias("empty"), *(F.max(c).alias(c) for c in ("cells", "most_row", "most_col"))
    )
    single = (F.col("most_row") <= 1) | (F.col("most_col") <= 1)
    return sums.select(F.coalesce(F.when(single, F.col("met")).otherwise(-F.col("cells") * F.expm1("empty")), F.lit(0.0)).alias("sketch_nnz"))


def degree_profile(x: DataFrame, side: str = "src") -> DataFrame:
    """degree, nodes: how many nodes have each degree."""
    return x.groupBy(side).agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("nodes"))


#: Columns of a result's summary.
SUMMARY = ("n_pairs", "sum_n", "max_n")


def summary(x: DataFrame) -> DataFrame:
    """n_pairs, sum_n, max_n of a result."""
    return x.agg(F.count("*").alias("n_pairs"), F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("sum_n"), F.coalesce(F.max("n"), F.lit(0)).cast("long").alias("max_n"))


# dense rows, for the baseline without sparsity


def dense_rows(x: DataFrame, cols: DataFrame, rows: DataFrame) -> DataFrame:
    """(src, vec): every row of the matrix as an array over all columns in the order of their keys, zeros included."""
    at = cols.select(F.col("id").alias("dst")).withColumn("one", F.lit(1)).groupBy("one").agg(F.array_sort(F.collect_list("dst")).alias("keys"))
    entries = x.groupBy("src").agg(F.map_from_entries(F.collect_list(F.struct("dst", F.col("n").cast("double")))).alias("entries"))
    full = rows.select(F.col("id").alias("src")).join(entries, "src", "left").withColumn("one", F.lit(1)).join(at, "one")
    return full.select("src", F.transform("keys", lambda k: F.coalesce(F.try_element_at("entries", k), F.lit(0.0))).alias("vec"))


def dense_multiply(x: DataFrame, middle: DataFrame, y: DataFrame) -> DataFrame:
    """Product of dense rows: each row's cells meet the right matrix's rows, zeros too."""
    keys = middle.select("id").withColumn("one", F.lit(1)).groupBy("one").agg(F.array_sort(F.collect_list("id")).alias("keys"))
    cells = x.withColumn("one", F.lit(1)).join(keys, "one").select("src", F.explode(F.arrays_zip("keys", "vec")).alias("c"))
    right = y.select(F.col("src").alias("k"), F.col("vec").alias("row"))
    terms = cells.select("src", F.col("c.keys").alias("k"), F.col("c.vec").alias("v")).join(right, "k")
    placed = terms.select("src", F.posexplode(F.transform("row", lambda r: r * F.col("v"))).alias("at", "part"))
    sums = placed.groupBy("src", "at").agg(F.sum("part").alias("s"))
    return sums.groupBy("src").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "s"))), lambda e: e["s"]).alias("vec"))


def sparse_rows(x: DataFrame, cols: DataFrame) -> DataFrame:
    """(src, dst, n) of dense rows without zeros."""
    keys = cols.select("id").withColumn("one", F.lit(1)).groupBy("one").agg(F.array_sort(F.collect_list("id")).alias("keys"))
    cells = x.withColumn("one", F.lit(1)).join(keys, "one").select("src", F.explode(F.arrays_zip("keys", "vec")).alias("c"))
    return cells.filter("c.vec <> 0").select("src", F.col("c.keys").alias("dst"), F.round("c.vec").cast("long").alias("n"))


#: Rows and columns of a tile, middle nodes that meet in one task, and those whose zeros are filled in at a time.
TILE, TILE_MIDDLE, STRIP = 2048, 8192, 1024


def dense_tiles(x: DataFrame, y: DataFrame, rows: int, middle: int, cols: int) -> DataFrame:
    """The product of dense matrices of any size, as (src, dst, n) without zeros.

    A task gets the entries of one tile of each side, fills in the zeros and multiplies the arrays, so no array is
    larger than a tile. Tiles that differ only in their middle nodes are summed.
    """
    deal = lambda c, n, most: F.pmod(F.xxhash64(c), F.lit(max(1, math.ceil(n / most)))).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(max(1, math.ceil(n / TILE)) - 1)))
    left = x.select("src", "dst", "n", deal("src", rows, TILE).alias("i"), deal("dst", middle, TILE_MIDDLE).alias("m"), every(cols).alias("j"))
    right = y.select("src", "dst", "n", every(rows).alias("i"), deal("src", middle, TILE_MIDDLE).alias("m"), deal("dst", cols, TILE).alias("j"))
    tiles = left.groupBy("i", "m", "j").cogroup(right.groupBy("i", "m", "j")).applyInArrow(_tile_product, "src long, dst long, n double")
    return tiles.groupBy("src", "dst").agg(F.round(F.sum("n")).cast("long").alias("n"))


def _tile_product(left: pa.Table, right: pa.Table) -> pa.Table:
    a, kx, nx, kdst, b, ny = (np.asarray(t.column(c)) for t, c in ((left, "src"), (left, "dst"), (left, "n"), (right, "src"), (right, "dst"), (right, "n")))
    (sources, at), (targets, to) = np.unique(a, return_inverse=True), np.unique(b, return_inverse=True)
    nodes = np.union1d(kx, kdst)
    inner, outer = np.searchsorted(nodes, kx), np.searchsorted(nodes, kdst)
    first, second = np.argsort(inner, kind="stable"), np.argsort(outer, kind="stable")
    sums = np.zeros((len(sources), len(targets)))
    for start in range(0, len(nodes), STRIP):
        p, q = (o[slice(*np.searchsorted(k[o], (start, start + STRIP)))] for o, k in ((first, inner), (second, outer)))
        u, v = np.zeros((len(sources), STRIP)), np.zeros((STRIP, len(targets)))
        u[at[p], inner[p] - start] = nx[p]
        v[outer[q] - start, to[q]] = ny[q]
        sums += u @ v
    i, j = np.nonzero(sums)
    return pa.table({"src": pa.array(sources[i].astype(np.int64)), "dst": pa.array(targets[j].astype(np.int64)), "n": pa.array(sums[i, j])})
