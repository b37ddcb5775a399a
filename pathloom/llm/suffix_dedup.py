"""Removal of repeated byte strings, blockwise over suffix buckets with a difference cover.

A string of ``length`` bytes that occurs twice, at i and at j, has an offset below the cover's period v
at which both occurrences hit positions of the cover (a perfect difference set modulo v, counted from
each document's start). So the suffixes at cover positions, compared by their first ``length - v + 1``
bytes, tell which parts of which documents can hold repeats at all. Only the windows there are
ranked, one suffix bucket at a time: a bucket is a range of fingerprints, of bounded size, and within it
the windows are sorted by fingerprints, document and place; all but the first of equal ones are repeats.
No suffix is sorted: the result needs equality and first occurrence but no alphabetic order, so windows are
ranked by two independent 64-bit fingerprints, 128 bits together, and their bytes are not compared.

Both passes reduce within slices of the input before they shuffle (a string that is common everywhere
is sent once per slice), texts that occur more than once are ranked once, and texts themselves
are not shuffled while the tables joined to them are small.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BROADCAST_BYTES, pick, shuffles_dropped, stored, table
from .memory import released

LENGTH = 100
#: A perfect difference set. Every difference modulo 57 is that of exactly one pair.
PERIOD, COVER = 57, (0, 1, 3, 13, 32, 36, 43, 52)
SLICE_BYTES = 4 << 20
LEAST_BITS = 10
BUCKET_WINDOWS = 4_000_000
#: Rounds of the second pass for texts of more bytes than this: each ranks its share of the buckets, and what it shuffled goes before the next.
ROUNDS, ROUND_BYTES = 2, 32 << 20

_ROW = "part int, slice long, kind int, a binary, b binary, c binary, d binary"
_NAMES = ["part", "slice", "kind", "a", "b", "c", "d"]
_ODD, _ODD_TOO = (np.random.Generator(np.random.PCG64(seed)).integers(1, 1 << 63, 16).astype(np.uint64) * np.uint64(2) + np.uint64(1) for seed in (7, 11))


def _planes(x: np.ndarray, width: int) -> bytes:
    """The low width bytes of unsigned integers, byte plane by byte plane, so that constant planes compress."""
    return np.ascontiguousarray(x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T).tobytes()


def _numbers(data: bytes, width: int) -> np.ndarray:
    planes = np.frombuffer(data, np.uint8).reshape(width, -1)
    out = np.zeros((planes.shape[1], 8), np.uint8)
    out[:, :width] = planes.T
    return out.view("<u8").ravel()


def _fingerprints(data: np.ndarray, at: np.ndarray, length: int, odd: np.ndarray = _ODD) -> np.ndarray:
    """64-bit fingerprints of the strings of length bytes at the given places, by a table of odd factors."""
    eight = np.ndarray((len(data) - 7,), "<u8", data, 0, (1,))
    out = np.full(len(at), length, np.uint64)
    for i, step in enumerate([*range(0, length - 8, 8), length - 8]):
        x = eight[at + step]
        x ^= x >> np.uint64(29)
        x *= odd[i % 15]
        out ^= x
        out *= odd[15]
        out ^= out >> np.uint64(32)
    return out


class _Slice:
    """Some documents in the order of their ids, as one run of bytes; places count one gap after each document."""

    def __init__(self, rows: pa.RecordBatch):
        order = np.argsort(rows.column("key").to_numpy(zero_copy_only=False), kind="stable")
        rows = rows.take(pa.array(order))
        text = rows.column("text").cast(pa.large_binary())
        self.keys = rows.column("key").to_numpy(zero_copy_only=False)
        self.digests = b"".join(rows.column("digest").to_pylist())
        ends = np.frombuffer(text.buffers()[1], np.int64)[text.offset : text.offset + len(text) + 1]
        self.lengths = np.diff(ends)
        data = np.frombuffer(text.buffers()[2] or b"", np.uint8)[ends[0] : ends[-1]]
        self.data = np.concatenate([data, np.zeros(16, np.uint8)])
        self.raw = ends[:-1] - ends[0]
        self.id = xxhash.xxh3_64_intdigest(self.digests) - (1 << 63)
        self.rows = rows

    def header(self, local: bytes) -> tuple:
        return (-1 - self.id % 997, self.id, 1, self.digests, _planes(self.lengths, 5), local, b"")


def _slices(batches: Iterator[pa.RecordBatch]) -> Iterator[_Slice]:
    for batch in batches:
        ends = np.cumsum(pc.binary_length(batch.column("text")).to_numpy(zero_copy_only=False))
        at = 0
        while at < batch.num_rows:
            base = ends[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(ends, base + SLICE_BYTES, "right")))
            yield _Slice(batch.slice(at, to - at))
            at = to


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = [pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.binary()]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=_NAMES)


def _parts(part: np.ndarray) -> Iterator[tuple[int, int, int]]:
    """(part, from, to) of each run of a sorted array."""
    cuts = np.flatnonzero(np.diff(part)) + 1
    for i, j in zip([0, *cuts], [*cuts, len(part)], strict=True):
        if j > i:
            yield int(part[i]), int(i), int(j)


def _cover_samples(bits: int, length: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """First pass: the suffixes at cover positions, one of equal ones for each slice, dealt to buckets."""
    prefix, steps = length - PERIOD + 1, np.array(COVER)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for s in _slices(batches):
            blocks = np.where(s.lengths >= length, -(-s.lengths // PERIOD), 0)
            doc = np.repeat(np.arange(len(blocks)), blocks)
            number = np.arange(len(doc)) - np.repeat(np.cumsum(blocks) - blocks, blocks)
            place = (number[:, None] * PERIOD + steps).ravel()
            doc = np.repeat(doc, len(steps))
            fits = place <= s.lengths[doc] - prefix
            doc, place = doc[fits], place[fits]
            if not len(doc):
                continue
            where = s.raw[doc] + place
            value = _fingerprints(s.data, where, prefix) >> np.uint64(24 - bits)
            where += doc
            _, first, which, count = np.unique(value, return_index=True, return_inverse=True, return_counts=True)
            again = where[count[which] > 1]
            rows = [s.header(_planes(again, 5))]
            value, where = value[first], where[first]
            part = (value >> np.uint64(40)).astype(np.int64)
            for p, i, j in _parts(part):
                rows.append((p, s.id, 0, _planes(value[i:j], 5), _planes(where[i:j], 5), b"", b""))
            yield _batch(rows)

    return run


def _shared_samples(rows: pd.DataFrame) -> pd.DataFrame:
    """One bucket of the first pass: the places whose suffix occurs in several slices; headers pass through."""
    rest, rows = rows[rows["kind"] == 1], rows[rows["kind"] == 0]
    out = []
    if len(rows):
        values = [_numbers(x, 5) for x in rows["a"]]
        whole = np.concatenate(values)
        order = np.argsort(whole, kind="stable")
        same = whole[order[1:]] == whole[order[:-1]]
        shared = np.zeros(len(whole), bool)
        shared[order[1:][same]] = True
        shared[order[:-1][same]] = True
        at = 0
        for v, where, slice_ in zip(values, rows["b"], rows["slice"], strict=True):
            mine = shared[at : at + len(v)]
            at += len(v)
            if mine.any():
                out.append((0, slice_, 0, b"", _planes(np.sort(_numbers(where, 5)[mine]), 5), b"", b""))
    return pd.concat([rest[_NAMES], pd.DataFrame(out, columns=_NAMES)]) if out else rest[_NAMES]


def _open_ranges(length: int):
    def run(rows: pd.DataFrame) -> pd.DataFrame:
        """One slice of the first pass: for each of its documents, the ranges of windows that can have an equal elsewhere."""
        head = rows[rows["kind"] == 1].iloc[0]
        n = _numbers(head["b"], 5).astype(np.int64)
        start = np.concatenate([[0], np.cumsum(n + 1)[:-1]])
        where = np.concatenate([_numbers(x, 5) for x in [head["c"], *rows[rows["kind"] == 0]["b"]]]).astype(np.int64)
        where.sort()
        doc = np.searchsorted(start, where, "right") - 1
        low = np.maximum(where - PERIOD + 1, start[doc])
        high = np.minimum(where + 1, start[doc] + n[doc] - length + 1)
        low, high = _union(low[high > low], high[high > low])
        doc = np.searchsorted(start, low, "right") - 1
        out = [(head["a"][16 * p : 16 * p + 16], np.stack([low[i:j] - start[p], high[i:j] - start[p]]).astype("<i4").tobytes()) for p, i, j in _parts(doc)]
        return pd.DataFrame(out, columns=["digest", "ranges"])

    return run


def _union(low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The union of intervals as disjoint ones that do not touch, in order."""
    if not len(low):
        return low, high
    order = np.argsort(low, kind="stable")
    low, high = low[order], np.maximum.accumulate(high[order])
    new = np.concatenate([[True], low[1:] > high[:-1]])
    last = np.concatenate([np.flatnonzero(new)[1:] - 1, [len(low) - 1]])
    return low[new], high[last]


def _open_windows(bits: int, length: int, number: int = 0, rounds: int = 1) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Second pass: all windows in open ranges, the first of equal ones in each slice, dealt to buckets; of several rounds, one's buckets."""
    width = -(-(64 - bits) // 8)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for s in _slices(batches):
            ranges = [np.frombuffer(r, "<i4").reshape(2, -1) for r in s.rows.column("ranges").to_pylist()]
            doc = np.repeat(np.arange(len(ranges)), [r.shape[1] for r in ranges])
            low, high = np.concatenate(ranges, axis=1).astype(np.int64)
            many = high - low
            doc = np.repeat(doc, many)
            place = np.arange(len(doc)) - np.repeat(np.cumsum(many) - many - low, many)
            where = s.raw[doc] + place
            value = _fingerprints(s.data, where, length)
            if rounds > 1:
                mine = (value >> np.uint64(64 - bits)) % np.uint64(rounds) == number
                value, where, doc = value[mine], where[mine], doc[mine]
                if not len(value):
                    continue
            second = _fingerprints(s.data, where, length, _ODD_TOO)
            where += doc
            _, first, which = np.unique(value, return_index=True, return_inverse=True)
            ahead = second != second[first][which]
            ahead[first] = True
            left, right = _union(where[~ahead], where[~ahead] + 1)
            rows = [s.header(_planes(np.concatenate([left, right]), 5))]
            value, second, where, doc = value[ahead], second[ahead], where[ahead], doc[ahead]
            part = (value >> np.uint64(64 - bits)).astype(np.int64)
            order = np.argsort(part.astype(np.uint16) if bits <= 16 else part, kind="stable")
            part, value, second, where, doc = part[order], value[order], second[order], where[order], doc[order]
            for p, i, j in _parts(part):
                d = doc[i:j]
                turns = np.concatenate([[0], np.flatnonzero(np.diff(d)) + 1])
                runs = np.diff(np.concatenate([turns, [j - i]]))
                rows.append((p, s.id, 0, _planes(value[i:j], width) + _planes(second[i:j], 8), _planes(where[i:j], 5), _planes(s.keys[d[turns]].astype(np.int64), 8), _planes(runs, 4)))
            yield _batch(rows)

    return run


def _later_windows(bits: int):
    width = -(-(64 - bits) // 8)

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        """One bucket of the second pass: the windows that are not the first of their content."""
        rest, rows = rows[rows["kind"] == 1], rows[rows["kind"] == 0]
        out = []
        if len(rows):
            many = [len(x) // (width + 8) for x in rows["a"]]
            value = np.concatenate([_numbers(x[: n * width], width) for x, n in zip(rows["a"], many, strict=True)])
            second = np.concatenate([_numbers(x[n * width :], 8) for x, n in zip(rows["a"], many, strict=True)])
            doc = np.concatenate([np.repeat(_numbers(d, 8).view(np.int64), _numbers(n, 4).astype(np.int64)) for d, n in zip(rows["c"], rows["d"], strict=True)])
            slice_ = np.repeat(rows["slice"].to_numpy(np.int64), many)
            order = np.lexsort((slice_, doc, second, value))
            later = np.zeros(len(value), bool)
            later[order[1:]] = (value[order[1:]] == value[order[:-1]]) & (second[order[1:]] == second[order[:-1]])
            at = 0
            for n, where, s in zip(many, rows["b"], rows["slice"], strict=True):
                mine = later[at : at + n]
                at += n
                if mine.any():
                    out.append((0, s, 0, b"", _planes(_numbers(where, 5)[mine], 5), b"", b""))
        return pd.concat([rest[_NAMES], pd.DataFrame(out, columns=_NAMES)]) if out else rest[_NAMES]

    return run


def _spans(length: int):
    def run(rows: pd.DataFrame) -> pd.DataFrame:
        """One slice of the second pass: for each document with repeats, what is removed and the stretches that stay."""
        head = rows[rows["kind"] == 1].iloc[0]
        n = _numbers(head["b"], 5).astype(np.int64)
        start = np.concatenate([[0], np.cumsum(n + 1)[:-1]])
        left, right = np.concatenate([_numbers(c, 5).astype(np.int64).reshape(2, -1) for c in rows[rows["kind"] == 1]["c"]], axis=1)
        where = np.concatenate([np.empty(0, np.uint64), *(_numbers(x, 5) for x in rows[rows["kind"] == 0]["b"])]).astype(np.int64)
        low, high = _union(np.concatenate([left, where]), np.concatenate([right, where + 1]) + length - 1)
        doc = np.searchsorted(start, low, "right") - 1
        out = []
        for p, i, j in _parts(doc):
            a, b = low[i:j] - start[p], high[i:j] - start[p]
            begin, end = np.concatenate([[0], b]), np.concatenate([a, [n[p]]])
            some = end > begin
            out.append((head["a"][16 * p : 16 * p + 16], int((b - a).sum()), len(a), begin[some].tolist(), (end - begin)[some].tolist()))
        return pd.DataFrame(out, columns=["digest", "n_removed", "n_spans", "starts", "sizes"])

    return run


def _joined(docs: DataFrame, few: DataFrame, row_bytes: str, how: str) -> DataFrame:
    """docs joined to few on digest; few is sent to all executors only while its measured bytes allow it."""
    size = few.agg(F.sum(F.expr(row_bytes))).first()[0] or 0
    return docs.join(F.broadcast(few) if size <= BROADCAST_BYTES else few, "digest", how)


def repeated_spans(docs: DataFrame, length: int = LENGTH, key: str = "doc_id", text: str = "text", carry: tuple[str, ...] = ()) -> DataFrame:
    """The rows of docs with what is repeated in them: columns key, text, those to carry, n_bytes, n_removed, n_spans, starts, sizes.

    A byte is removed if a string of ``length`` bytes over it also starts earlier: in a row with a
    smaller key, or earlier in the same row. starts and sizes are the stretches of bytes that stay. Null texts
    are empty. Rows with a null key come before all others. Of rows with equal texts the smallest key
    is the first; rows that repeat a key and a text are each treated as that first one; among
    different texts with one key an order is chosen by content. Extra columns are ignored.
    """
    if length < PERIOD + 8:
        raise ValueError(f"length must be at least {PERIOD + 8}")
    carried = [f"carried{i}" for i in range(len(carry))]
    rows = pick(docs, key, text, *carry).toDF("key", "text", *carried)
    rows = rows.select(F.col("key").cast("long").alias("key"), F.coalesce("text", F.lit("")).alias("text"), *carried)
    order = F.coalesce("key", F.lit(-(1 << 63)))
    rows = rows.withColumn("digest", F.unhex(F.md5("text"))).withColumn("order", order)
    facts = stored(rows.select("order", "digest", F.octet_length("text").cast("long").alias("n")), "text-keys")
    total = facts.agg(F.sum("n")).first()[0] or 0
    bits = max(LEAST_BITS, int(np.ceil(np.log2(max(1, total * len(COVER) / PERIOD / BUCKET_WINDOWS)))))
    bits = min(bits, 24)  # buckets get larger beyond 2**24 of them, some 500 TB of text
    copies = stored(facts.groupBy("digest").agg(F.count("*").alias("c"), F.min("order").alias("first")).filter("c > 1").select("digest", "first"), "copies")
    rows = _joined(rows, copies, "24", "left")
    is_copy = F.col("first").isNotNull() & (F.col("order") != F.col("first"))
    own = rows.filter(~is_copy & (F.octet_length("text") >= length)).select(F.col("order").alias("key"), "digest", "text")
    twice = facts.groupBy("digest", "order").count().filter("count > 1").select("digest").distinct()
    if not twice.isEmpty():  # rows that repeat a key and a text: one of them is ranked
        own = _joined(own, twice, "24", "left_anti").union(_joined(own, twice, "24", "left_semi").dropDuplicates(["digest"]).select("digest", "key", "text"))

    sent = own.mapInArrow(released(_cover_samples(bits, length)), _ROW)
    shared = sent.groupBy("part").applyInPandas(_shared_samples, _ROW)
    with shuffles_dropped(docs.sparkSession):
        ranges = stored(shared.groupBy("slice").applyInPandas(_open_ranges(length), "digest binary, ranges binary"), "ranges")

    near = _joined(own, ranges, "24 + length(ranges)", "inner").select("key", "digest", "text", "ranges")
    rounds = ROUNDS if total > ROUND_BYTES else 1
    found = []
    for number in range(rounds):
        sent = near.mapInArrow(released(_open_windows(bits, length, number, rounds)), _ROW)
        found.append(sent.groupBy("part").applyInPandas(_later_windows(bits), _ROW))
        if rounds > 1:
            with shuffles_dropped(docs.sparkSession):
                found[-1] = stored(found[-1], "later")
    later = reduce(DataFrame.union, found)
    with shuffles_dropped(docs.sparkSession):
        spans = stored(
            later.groupBy("slice").applyInPandas(_spans(length), "digest binary, n_removed long, n_spans long, starts array<long>, sizes array<long>"), "spans"
        )
    out = _joined(rows, spans, "40 + 16 * size(starts)", "left")
    none = F.array().cast("array<long>")
    n = F.octet_length("text").cast("long")
    whole = is_copy & (n >= length)
    return out.select(
        F.col("key").alias(key),
        F.col("text").alias(text),
        *(F.col(c).alias(name) for c, name in zip(carried, carry, strict=True)),
        n.alias("n_bytes"),
        F.when(whole, n).otherwise(F.coalesce("n_removed", F.lit(0))).cast("long").alias("n_removed"),
        F.when(whole, 1).otherwise(F.coalesce("n_spans", F.lit(0))).cast("long").alias("n_spans"),
        F.when(whole, none).otherwise(F.coalesce("starts", F.array(F.lit(0)).cast("array<long>"))).alias("starts"),
        F.when(whole, none).otherwise(F.coalesce("sizes", F.array(n))).alias("sizes"),
    )


def kept_bytes(text: Column, starts: Column, sizes: Column) -> Column:
    """The stretches that stay, concatenated, as binary."""
    data = text.cast("binary")
    return F.aggregate(
        F.arrays_zip(starts.alias("s"), sizes.alias("n")),
        F.lit(b""),
        lambda done, x: F.concat(done, F.substring(data, (x["s"] + 1).cast("int"), x["n"].cast("int"))),
    )


def kept_text(text: Column, starts: Column, sizes: Column) -> Column:
    """The stretches that stay, as text: characters of which a byte stays, stay whole."""
    data = text.cast("binary")

    def inside(at: Column) -> Column:
        """Is the byte at a place one that goes on a character."""
        return F.hex(F.substring(data, (at + 1).cast("int"), F.lit(1))).between("80", "BF")

    def stretch(x: Column) -> Column:
        begin, end = x["s"], x["s"] + x["n"]
        back = F.when(inside(begin), F.when(inside(begin - 1), F.when(inside(begin - 2), 3).otherwise(2)).otherwise(1)).otherwise(0)
        on = F.when(inside(end), F.when(inside(end + 1), F.when(inside(end + 2), 3).otherwise(2)).otherwise(1)).otherwise(0)
        return F.substring(data, (begin - back + 1).cast("int"), (end + on - begin + back).cast("int")).cast("string")

    return F.array_join(F.transform(F.arrays_zip(starts.alias("s"), sizes.alias("n")), stretch), "")


def op7_difference_cover_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = repeated_spans(table(spark, sf_dir, "documents"))
    kept = F.when(F.col("n_removed") == 0, F.sha2(F.col("text"), 256)).otherwise(F.sha2(kept_bytes(F.col("text"), F.col("starts"), F.col("sizes")), 256))
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", kept.alias("kept_sha256"))
