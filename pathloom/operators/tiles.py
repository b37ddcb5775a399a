"""Products of a matrix with its own transpose that take far more scalar products than it has entries.

A shuffle of products, even of partial sums, would fill the disks. Here only entries are shuffled: a task gets all
entries of two ranges of sources, so its sums are complete, and it hands them on, or only their summary, a few rows at
a time. Pairs of ranges on one side of the diagonal are computed, the others mirrored.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .matrix import SUMMARY
from .memory import Matrix, ones, product_parts

#: Scalar products from which, and entries' share of them up to which, products are made so; scalar products and entries of a task.
LEAST_OPERATIONS, LEAST_RATIO, TILE_OPERATIONS, TILE_ENTRIES = 1e8, 64, 5e8, 8e6
#: Cells of a dense product a scalar product up to which arrays with zeros are multiplied, and cells of those at a time.
FULL_CELLS, STRIP_CELLS = 32, 1 << 20


def dealt_by_entries(operations: float, entries: float) -> bool:
    return operations >= LEAST_OPERATIONS and operations > LEAST_RATIO * entries


def squared_by_tiles(x: DataFrame, operations: float, entries: float) -> DataFrame:
    """x times its own transpose, as (src, dst, n)."""
    return _tiles(x, operations, entries, _pairs, "src long, dst long, n long")


def squared_summary(x: DataFrame, operations: float, entries: float) -> DataFrame:
    """n_pairs, sum_n, max_n of x times its own transpose, whose pairs are summed up where they are made."""
    found = _tiles(x, operations, entries, _summary, "pairs long, total long, most long")
    columns = (("n_pairs", F.sum("pairs")), ("sum_n", F.sum("total")), ("max_n", F.max("most")))
    return found.agg(*(F.coalesce(c, F.lit(0)).cast("long").alias(name) for name, c in columns)).select(*SUMMARY)


def _tiles(x: DataFrame, operations: float, entries: float, made: Callable, schema: str) -> DataFrame:
    side = max(1, math.ceil(math.sqrt(operations / TILE_OPERATIONS)), math.ceil(2 * entries / TILE_ENTRIES))
    rows = x.groupBy("src").agg(F.collect_list("dst").alias("dst"), F.collect_list("n").alias("n"))
    here, there = F.pmod(F.xxhash64("src"), F.lit(side)).cast("int"), F.explode(F.sequence(F.lit(0), F.lit(side - 1)))
    dealt = rows.withColumn("here", here).withColumn("there", there)
    tiles = dealt.select(F.least("here", "there").alias("i"), F.greatest("here", "there").alias("j"), (F.col("here") > F.col("there")).alias("right"), "src", "dst", "n")
    return tiles.repartition(2 * side * (side + 1), "i", "j").groupBy("i", "j").applyInArrow(made, schema)


def _read(batches: Iterator[pa.RecordBatch]) -> list[tuple[np.ndarray, ...]]:
    """The sides of a tile, one on the diagonal, as (sources, entries of each, middle nodes, n)."""
    found: tuple[list, list] = ([], [])
    for batch in batches:
        dst, n = (batch.column(c) for c in ("dst", "n"))
        right = np.asarray(batch.column("right"))
        for k in (0, 1):
            at = pa.array(np.flatnonzero(right == bool(k)))
            if len(at):
                d, m = dst.take(at), n.take(at)
                found[k].append((np.asarray(batch.column("src").take(at)), np.diff(np.asarray(d.offsets)), np.asarray(d.flatten()), _lean(np.asarray(m.flatten()))))
    return [tuple(_joined(list(c)) for c in zip(*f, strict=True)) for f in found if f]


def _lean(n: np.ndarray) -> np.ndarray:
    return ones(len(n)) if (n == 1).all() else n


def _joined(arrays: list[np.ndarray]) -> np.ndarray:
    if all(a.strides == (0,) and a[0] == 1 for a in arrays):
        return ones(sum(map(len, arrays)))
    return np.concatenate(arrays)


def _sums(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> tuple[bool, Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]]:
    """Is a tile on the diagonal, and its (src, dst, n), some rows at a time."""
    i, j = (k.as_py() for k in key)
    sides = _read(batches)
    if i != j and len(sides) < 2:
        return False, iter(())
    nodes = np.unique(np.concatenate([np.unique(s[2]) for s in sides]))
    matrices = []
    for sources, many, middle, n in sides:
        order = np.argsort(sources)
        at = np.empty(len(order), np.int32)
        at[order] = np.arange(len(order), dtype=np.int32)
        src, dst = np.repeat(at, many), np.searchsorted(nodes, middle).astype(np.int32)
        place = np.argsort(src, kind="stable")
        matrices.append((sources[order], Matrix(len(sources), len(nodes), src[place], dst[place], n if n.strides == (0,) else n[place])))
    (sources, x), (targets, z) = matrices[0], matrices[-1]

    def found() -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        into, outof = np.bincount(x.dst, minlength=len(nodes)), np.bincount(z.dst, minlength=len(nodes))
        full = x.rows * z.rows * len(nodes) < FULL_CELLS * int((into * outof).sum())
        for src, dst, n in _full(x, z) if full else product_parts(x, z.turned())[1]:
            yield sources[src], targets[dst], n

    return i == j, found()


def _full(x: Matrix, z: Matrix) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """The product of x and z transposed, zeros filled in. All sums are below 2^53, else they are refused."""
    right = np.zeros((z.cols, z.rows))
    right[z.dst, z.src] = z.n
    step = max(1, STRIP_CELLS // max(1, z.rows))
    for start in range(0, x.rows, step):
        at = slice(*np.searchsorted(x.src, (start, start + step)))
        left = np.zeros((min(step, x.rows - start), x.cols))
        left[x.src[at] - start, x.dst[at]] = x.n[at]
        sums = left @ right
        if sums.size and sums.max() >= 2.0**53:
            raise OverflowError("sums of this product are too large to be exact")
        i, j = np.nonzero(sums)
        yield i + start, j, sums[i, j].astype(np.int64)


def _summary(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    diagonal, found = _sums(key, batches)
    pairs = total = most = 0
    for _, _, n in found:
        if len(n):
            pairs, total, most = pairs + len(n), total + int(n.sum()), max(most, int(n.max()))
    times = 1 if diagonal else 2
    yield pa.RecordBatch.from_arrays([pa.array([v], pa.int64()) for v in (times * pairs, times * total, most)], names=["pairs", "total", "most"])


def _pairs(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    diagonal, found = _sums(key, batches)
    for src, dst, n in found:
        for a, b in ((src, dst),) if diagonal else ((src, dst), (dst, src)):
            yield pa.RecordBatch.from_arrays([pa.array(v.astype(np.int64, copy=False)) for v in (a, b, n)], names=["src", "dst", "n"])
