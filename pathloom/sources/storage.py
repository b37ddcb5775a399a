"""Tables in a folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, LongType, MapType, StringType, StructField, StructType

WORKLOAD_SCHEMA = StructType(
    [
        StructField("pos", IntegerType()),
        StructField("session", IntegerType()),
        StructField("path", StringType()),
        StructField("constraints", MapType(IntegerType(), StringType())),
    ]
)
LOG_SCHEMA = "pos int, session int, path string, constraints map<string,string>"
MATRIX_SCHEMA = StructType([StructField(c, LongType()) for c in ("src", "dst", "n")])
METRICS_SCHEMA = StructType(
    [
        StructField("engine", StringType()),
        StructField("pos", IntegerType()),
        StructField("path", StringType()),
        StructField("plan_seconds", DoubleType()),
        StructField("exec_seconds", DoubleType()),
        StructField("products", IntegerType()),
        StructField("cached_spans", IntegerType()),
        StructField("offers", IntegerType()),
        StructField("evictions", IntegerType()),
        StructField("rejected", IntegerType()),
        StructField("whole_hits", IntegerType()),
        StructField("keyed_hits", IntegerType()),
        StructField("resident_bytes", DoubleType()),
        StructField("cost", DoubleType()),
        StructField("operations", LongType()),
    ]
)


def shared_dir(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir (or by setCheckpointDir), which driver and executors share.

    Where neither is set, a temporary folder, but only if driver and executors are one process.
    """
    context = spark.sparkContext
    found = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not found:
        if context.master != "local" and not context.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="pathloom-"))
        found = context.getCheckpointDir()
    return found


def fresh_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/matrices/{label}-{uuid.uuid4().hex}"


def stored(df: DataFrame, label: str = "table") -> DataFrame:
    """df as a table in the shared folder: its lineage is cut and it is computed once."""
    path = fresh_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def stored_counted(df: DataFrame, label: str = "table") -> tuple[DataFrame, int]:
    """As stored, with the number of rows, counted while they are written."""
    rows = Observation()
    return stored(df.observe(rows, F.count(F.lit(1)).alias("n")), label), rows.get["n"]


@contextmanager
def shuffles_dropped(spark: SparkSession) -> Iterator[None]:
    """What is executed within leaves no shuffled files behind, whether or not the JVM collects garbage."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, "false")
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.set(key, before)


def dropped(table: DataFrame) -> None:
    """Delete the files of a table that stored gave."""
    spark = table.sparkSession
    for folder in {f.rsplit("/", 1)[0] for f in table.inputFiles()}:
        if "/matrices/" in folder:
            at = spark._jvm.org.apache.hadoop.fs.Path(folder)
            at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def bounded_column(df: DataFrame, most: int = 50_000_000) -> np.ndarray:
    """A one-column DataFrame as an array on the driver, in its order; refused beyond ``most`` rows."""
    found = df.limit(most + 1).toArrow()
    if found.num_rows > most:
        raise ValueError(f"more than {most} rows are too many for the driver")
    return found.column(0).to_numpy()


def read_table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def read_edges(spark: SparkSession, path: str, kind: str = "csv", header: bool = True) -> DataFrame:
    """Edges (src, dst: longs) from a file of a kind: csv, orc, json or parquet."""
    reader = spark.read.schema("src long, dst long")
    return reader.option("header", header).csv(path) if kind == "csv" else reader.format(kind).load(path)


def read_workload(spark: SparkSession, path: str) -> DataFrame:
    """A query log of JSON lines with the workload's columns; positions are names there."""
    return typed_log(spark.read.schema(LOG_SCHEMA).json(path))


def typed_log(log: DataFrame) -> DataFrame:
    """A log read with LOG_SCHEMA, streamed or not, with positions as numbers."""
    return log.withColumn("constraints", F.transform_keys("constraints", lambda k, v: k.cast("int")))


def write_results(df: DataFrame, path: str, mode: str = "overwrite", by: str | None = None, kind: str = "parquet") -> None:
    """A result as files of a kind, partitioned by a column if one is named; kind noop computes it without writing."""
    writer = df.write.mode(mode).format(kind)
    (writer.partitionBy(by) if by else writer).save(*([] if kind == "noop" else [path]))


def write_bucketed(df: DataFrame, name: str, buckets: int, key: str) -> DataFrame:
    """df as a catalog table bucketed and sorted by a join key, so that joins on it need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)
    return df.sparkSession.table(name)
