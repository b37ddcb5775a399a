"""Document fingerprints by a threshold-scaled sketch.

The sketch of a text holds every hash of its word shingles that is below a fixed fraction of the hash
range. It grows with the text, so two sketches of very unequal texts still give an unbiased estimate of
resemblance and containment, and the sketch of a union is the union of the sketches. A text that
has words but no hash below the threshold keeps its smallest one, so that short texts can be told apart;
that rule is mergeable too, since such a hash gives way to any below the threshold.

To compare each document with its neighbour in the order of ids, documents are dealt to contiguous ranges of
ids and text digests of about equal bytes. Only ids, digests and sizes are sorted to find where ranges begin; each
row's range is then looked up among those beginnings. The top document of each range is sent to the next
range as well, so every range has all neighbours it needs and no task sees the whole order.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import pick, stored, table
from .memory import released
from .near_dedup import WordHashes, shingle_hashes, words

#: One of this many hashes is retained. A power of two.
SCALE = 4
#: Bytes of text in a range, and the most beginnings of ranges (of 24 bytes each) that are sent to the executors: beyond 100 TB ranges get larger.
RANGE_BYTES, MOST_RANGES = 32 << 20, 1_000_000
LARGE_RANGE_BYTES = 128 << 20


def sketch(text: str | None, memo: WordHashes, scale: int = SCALE) -> np.ndarray:
    """The retained hashes, sorted and distinct, cut so that those below the threshold have 32 bits.

    A lone value of more bits is the smallest hash of a text that has none below the threshold.
    """
    h = shingle_hashes(words(text), memo)
    low = h[h < np.uint64((1 << 64) // scale)]
    return np.unique((low if len(low) else h[:1]) >> np.uint64(33 - scale.bit_length()))


def merged(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The sketch of the union of two texts' shingles."""
    both = np.union1d(a, b)
    low = both[both < np.uint64(1 << 32)]
    return low if len(low) else both[:1]


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Estimated Jaccard similarity; texts without words are alike."""
    if not len(a) and not len(b):
        return 1.0
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both)


def containment(a: np.ndarray, b: np.ndarray) -> float:
    """Estimated share of a's shingles that are in b."""
    return len(np.intersect1d(a, b, assume_unique=True)) / len(a) if len(a) else 1.0


def written(s: np.ndarray) -> str:
    """Base64 of the hashes, four bytes each; a lone larger one has eight, after a tilde."""
    lone = len(s) == 1 and s[0] >> np.uint64(32)
    return ("~" if lone else "") + base64.b64encode(s.astype("<u8" if lone else "<u4").tobytes()).decode()


def read(s: str) -> np.ndarray:
    lone = s.startswith("~")
    return np.frombuffer(base64.b64decode(s[lone:]), "<u8" if lone else "<u4").astype(np.uint64)


def edited(text: str, following: str) -> str:
    """text with its last half replaced by as much of the following text's beginning, or all of it."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def _compared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come in ascending order of part and key; a row's neighbour is the row before it in its part."""
    memo = WordHashes()
    before: tuple[object, str, np.ndarray] | None = None
    for batch in batches:
        out = []
        for row in batch.to_pylist():
            own = sketch(row["text"], memo)
            if not row["ghost"]:
                _, text, near = before
                new = edited(row["text"], text)
                other = sketch(new, memo)
                digest = hashlib.sha256(new.encode("utf-8", "surrogatepass")).hexdigest()
                out.append((row["key"], len(row["text"]), digest, written(own), written(other), likeness(own, other), likeness(own, near)))
            before = (row["part"], row["text"], own)
        names = ["key", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]
        kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
        columns = list(zip(*out, strict=True)) if out else [[]] * len(kinds)
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=names)


def neighbour_fingerprints(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next for each row of docs.

    The next document is the one with the next smaller key (null keys are smallest, rows of one key are
    ordered by text), for the smallest the largest. A sole document is its own next. Null texts are empty;
    empty texts have an empty fingerprint and are alike among themselves only. Extra columns are ignored. Rows of
    one key, or without one, are spread over ranges by their texts' digests.
    """
    rows = pick(docs, key, text).toDF("key", "text").select(F.col("key").cast("long").alias("key"), F.coalesce("text", F.lit("")).alias("text"))
    # the digest's order is that of its first 63 bits and then the rest
    rows = rows.withColumn("order", F.coalesce("key", F.lit(-(1 << 63)))).withColumn("digest", F.md5("text"))
    rows = rows.withColumn("high", F.conv(F.substring("digest", 1, 15), 16, 10).cast("long")).withColumn("low", F.conv(F.substring("digest", 16, 15), 16, 10).cast("long"))
    begins, tops = _ranges(rows.select("order", "high", "low", (F.octet_length("text").cast("long") + 64).alias("n")))
    n = len(begins)
    shared = rows.sparkSession.sparkContext.broadcast((begins, tops))

    @F.pandas_udf("struct<part int, top boolean>")
    def placed(order: pd.Series, high: pd.Series, low: pd.Series) -> pd.DataFrame:
        begins, tops = shared.value
        own = np.array(list(zip(order, high, low, strict=True)), begins.dtype)
        part = np.maximum(np.searchsorted(begins, own, "right") - 1, 0)
        return pd.DataFrame({"part": part.astype("int32"), "top": own == tops[part]})

    here = F.struct(F.col("at.part").alias("part"), F.lit(False).alias("ghost"))
    there = F.struct(F.pmod(F.col("at.part") + 1, F.lit(max(n, 1))).cast("int").alias("part"), F.lit(True).alias("ghost"))
    sent = rows.withColumn("at", placed("order", "high", "low")).select("key", "order", "high", "low", "text", F.explode(F.when(F.col("at.top"), F.array(here, there)).otherwise(F.array(here))).alias("to"))
    dealt = (
        sent.select("key", "order", "high", "low", "text", "to.part", "to.ghost")
        .repartition(max(n, 1), "part")
        .sortWithinPartitions("part", F.desc("ghost"), "order", "high", "low")
        .select("key", "text", "part", "ghost")
    )
    return dealt.mapInArrow(released(_compared), _SCHEMA).withColumnRenamed("key", key)


_PLACE = np.dtype([("order", "<i8"), ("high", "<i8"), ("low", "<i8")])


def _ranges(facts: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """The first and the last place (order, high, low) of each range of about equal bytes; facts has those columns and n, bytes.

    Rows of one place stay in one range. Sums are taken within sorted stretches and shifted by the stretches before, so
    no task sees all rows.
    """
    spark = facts.sparkSession
    sorted_ = stored(facts.repartitionByRange("order", "high", "low").withColumn("stretch", F.spark_partition_id()), "text-places")
    total = sorted_.agg(F.sum("n")).first()[0] or 0
    least = 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    size = max(1, min(RANGE_BYTES, total // least), min(LARGE_RANGE_BYTES, total // 65_536), total // MOST_RANGES)
    before = Window.orderBy("stretch").rowsBetween(Window.unboundedPreceding, -1)  # one row for each stretch
    starts = sorted_.groupBy("stretch").agg(F.sum("n").alias("bytes")).select("stretch", F.coalesce(F.sum("bytes").over(before), F.lit(0)).alias("start"))
    running = Window.partitionBy("stretch").orderBy("order", "high", "low").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    summed = sorted_.withColumn("sum", F.sum("n").over(running)).join(F.broadcast(starts), "stretch")
    place = F.struct("order", "high", "low")
    found = summed.groupBy(((F.col("start") + F.col("sum") - 1) / size).cast("long").alias("range")).agg(F.min(place).alias("first"), F.max(place).alias("last"))
    rows = found.select("first.*", F.col("last.order").alias("o"), F.col("last.high").alias("h"), F.col("last.low").alias("l")).toArrow()  # one row for each range
    columns = [c.to_numpy() for c in rows.columns]
    begins, tops = np.empty(rows.num_rows, _PLACE), np.empty(rows.num_rows, _PLACE)
    for name, a, b in zip(_PLACE.names, columns[:3], columns[3:], strict=True):
        begins[name], tops[name] = a, b
    order = np.argsort(begins, order=_PLACE.names)
    return begins[order], tops[order]


_SCHEMA = "key long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def op8_threshold_sketches(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neighbour_fingerprints(table(spark, sf_dir, "documents"))
