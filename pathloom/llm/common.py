"""What the corpus operators share: safe column picking, shared-folder tables, size checks."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Largest table, in bytes of its columnar files' rows as estimated by row count times row width, that is sent to every executor.
BROADCAST_BYTES = 24 << 20
#: Spark's setting by which the files that an execution shuffled go when it ends.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def session(df: DataFrame) -> SparkSession:
    return df.sparkSession


def pick(df: DataFrame, *names: str) -> DataFrame:
    """Only the named columns, found by exact spelling.

    Other columns may clash with them in spelling or case; they are dropped by position, so no
    ambiguous reference can arise. Of several columns with the same exact name the first counts.
    """
    at = [df.columns.index(n) for n in names]
    plain = df.toDF(*(f"_{i}" for i in range(len(df.columns))))
    return plain.select(*(F.col(f"_{i}").alias(n) for i, n in zip(at, names, strict=True)))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, from spark.checkpoint.dir.

    Where it is unset, a temporary folder, but only if driver and executors are one process.
    """
    context = spark.sparkContext
    found = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not found:
        if context.master != "local" and not context.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="pathloom-"))
        found = context.getCheckpointDir()
    return found


@contextmanager
def shuffles_dropped(spark: SparkSession) -> Iterator[None]:
    """What is executed within leaves no shuffled files behind, whether or not the JVM collects garbage."""
    before = spark.conf.get(CLEANUP, "false")
    spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.set(CLEANUP, before)


def stored(df: DataFrame, label: str) -> DataFrame:
    """df written as a table in the shared folder and read back: its lineage is cut, and a lost executor costs no recomputation."""
    path = f"{shared_dir(df.sparkSession)}/tables/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def broadcast_if_small(df: DataFrame, row_bytes: int, rows: int | None = None) -> DataFrame:
    """df with a broadcast hint if its counted rows of row_bytes fit BROADCAST_BYTES; otherwise unhinted, for a shuffled join."""
    n = df.count() if rows is None else rows
    return F.broadcast(df) if n * row_bytes <= BROADCAST_BYTES else df
