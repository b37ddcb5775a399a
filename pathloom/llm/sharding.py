"""Sharding by proportional stratified interleaving.

Rows of each stratum (source) are put in a seeded random order; a row's fractional rank is its
mid-rank divided by the stratum's size. Sorting all rows by fractional rank interleaves the strata
in proportion, so any contiguous cut has the mixture of the whole. Cutting at equal row counts gives
shards whose counts differ by one at most (law ``rows``).

No task ever holds a stratum: both ranks are taken by bucket (a hash range, then a rank range) and
shifted by the buckets' running counts, so a source with most of the rows costs what its buckets cost.
The texts themselves are never shuffled; only ids, sizes and checksums are.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import pick, stored, table

ROWS_A_BUCKET = 100_000
LEAST_BUCKETS = 1024
#: Bytes added to each text's size.
ROW_OVERHEAD = 16


def interleaved_shards(
    docs: DataFrame, n_shards: int = 40, seed: int = 17, key: str = "doc_id", stratum: str = "source", text: str = "text"
) -> DataFrame:
    """One row per row of docs: key, stratum, size, text_crc32, shard (0..n_shards-1), slot (gapless from 0 within the shard).

    Null texts have size ROW_OVERHEAD and checksum 0, null strata form one stratum of their own,
    null and repeated keys are ordinary rows (equal rows are interchangeable, so their order is
    immaterial). An empty table gives an empty result; with fewer rows than shards some shards stay
    empty. Extra columns are ignored.
    """
    body = F.coalesce(F.col("text"), F.lit(""))
    rows = stored(
        pick(docs, key, stratum, text)
        .toDF("key", "stratum", "text")
        .select(
            "key",
            "stratum",
            (F.octet_length(body) + ROW_OVERHEAD).cast("long").alias("size"),
            F.crc32(body.cast("binary")).cast("long").alias("text_crc32"),
        )
        .withColumn("group", F.coalesce(F.concat(F.lit("s"), F.col("stratum").cast("string")), F.lit("n")))
        .withColumn("token", F.md5(F.concat_ws("|", F.lit(str(seed)), F.coalesce(F.col("key").cast("string"), F.lit("")), F.col("text_crc32").cast("string")))),
        "shard-rows",
    )
    total = rows.count()
    buckets = max(LEAST_BUCKETS, -(-total // ROWS_A_BUCKET))
    rows = rows.withColumn("bucket", F.floor(F.conv(F.substring("token", 1, 12), 16, 10).cast("long") * F.lit(buckets) / F.lit(1 << 48)).cast("int"))

    before = Window.partitionBy("group").orderBy("bucket")
    starts = (
        rows.groupBy("group", "bucket")
        .agg(F.count("*").alias("n"))
        .select(
            "group",
            "bucket",
            F.coalesce(F.sum("n").over(before.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("start"),
            F.sum("n").over(Window.partitionBy("group")).alias("members"),
        )
    )
    within = Window.partitionBy("group", "bucket").orderBy("token", "key", "text_crc32", "size")
    ranked = (
        rows.withColumn("at", F.row_number().over(within))
        .join(starts, ["group", "bucket"])
        .withColumn("share", (2 * (F.col("start") + F.col("at")) - 1) / (2 * F.col("members")))
        .withColumn("band", F.least(F.floor(F.col("share") * buckets), F.lit(buckets - 1)).cast("int"))
        .select("key", "stratum", "size", "text_crc32", "group", "token", "share", "band")
    )
    # one row for each of the buckets, however many rows there are in them
    bands = ranked.groupBy("band").agg(F.count("*").alias("n"))
    bands = bands.select("band", F.coalesce(F.sum("n").over(Window.orderBy("band").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("start"))
    order = Window.partitionBy("band").orderBy("share", "group", "token", "key", "text_crc32", "size")
    total = max(total, 1)
    placed = (
        ranked.withColumn("at", F.row_number().over(order))
        .join(bands, "band")
        .withColumn("rank", F.col("start") + F.col("at") - 1)
        .withColumn("shard", F.expr(f"rank * {n_shards}L div {total}L").cast("int"))
    )
    return placed.select(
        F.col("key").alias(key),
        F.col("stratum").alias(stratum) if stratum != key else F.col("stratum"),
        "size",
        "text_crc32",
        "shard",
        (F.col("rank") - F.expr(f"(shard * {total}L + {n_shards - 1}L) div {n_shards}L")).alias("slot"),
    )


def op9_proportional_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return interleaved_shards(table(spark, sf_dir, "documents")).select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit("rows").alias("law"),
        "shard",
        "slot",
        F.lit(None).cast("int").alias("grown_shard"),
        "source",
    )
