"""Query logs as streams: answering in micro-batches, and counts of overlaps by window."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupStateTimeout

from pathloom.functions.workload import subpaths
from pathloom.operators.engine import WorkloadEngine
from pathloom.plans.query import parse_path
from pathloom.sources.storage import fresh_path


def run_stream(log: DataFrame, engine: WorkloadEngine, checkpoint: str, sink: Callable[[DataFrame, int], None]) -> StreamingQuery:
    """Answer a streamed log (pos, path, constraints) batch by batch, in order of pos; sink gets each batch's summary."""

    def batch(df: DataFrame, number: int) -> None:
        rows = df.orderBy("pos").collect()  # a micro-batch of queries
        if rows:
            sink(engine.run([parse_path(r["path"], engine.net, r["constraints"]) for r in rows]), number)

    return log.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).start()


def overlap_counts(log: DataFrame, width: str, slide: str | None = None, gap: str | None = None, late: str = "10 minutes") -> DataFrame:
    """sub_path, start, f by tumbling, sliding or session window; log has ts and path and may be a stream."""
    spread = log.withWatermark("ts", late).select("ts", F.explode(subpaths(F.col("path"))).alias("sub_path"))
    frame = F.session_window("ts", gap) if gap else F.window("ts", width, slide) if slide else F.window("ts", width)
    counts = spread.groupBy("sub_path", frame.alias("w")).agg(F.count("*").alias("f"))
    return counts.select("sub_path", F.col("w.start").alias("start"), "f")


def deduplicated(log: DataFrame, late: str = "10 minutes") -> DataFrame:
    """A streamed log without repeated query ids within the watermark."""
    return log.withWatermark("ts", late).dropDuplicatesWithinWatermark(["query_id"])


def query_log_stream(spark: SparkSession, folder: str) -> DataFrame:
    """Events as a streamed query log (ts, user, path): each event type stands for a path."""
    schema = spark.read.parquet(f"{folder}/events.parquet").schema
    e = spark.readStream.schema(schema).parquet(f"{folder}/events.parquet*")
    return e.select(F.col("ts").cast("timestamp").alias("ts"), F.when(F.col("event_type").isin("view", "click"), "U-E-T").otherwise("U-E-K").alias("path"))


def completed(counts: DataFrame, mode: str = "complete") -> DataFrame:
    """The table that a streamed aggregation has come to when all input there is has been read.

    Each micro-batch's result is a table in the shared folder. Complete results replace one another; updates are
    all given, with the number of their batch.
    """
    spark = counts.sparkSession
    base = fresh_path(spark, "stream")

    def batch(df: DataFrame, number: int) -> None:
        df.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{base}/{'all' if mode == 'complete' else f'part{number}'}")

    run = counts.writeStream.outputMode(mode).foreachBatch(batch).option("checkpointLocation", f"{base}-state").trigger(availableNow=True).start()
    run.awaitTermination()
    if mode == "complete":
        return spark.read.parquet(f"{base}/all").drop("batch")
    return spark.read.option("recursiveFileLookup", True).parquet(base)


STATE = "sub_path string, f double, seen long, last double"


def overlap_states(log: DataFrame, half_life: float = 86_400.0, idle: str = "30 days") -> DataFrame:
    """sub_path, f, seen, last (seconds since 1970): each sub-path's decayed frequency, kept as state; a count halves every half_life seconds.

    A sub-path not seen for idle (by the watermark) is forgotten. Rows come out whenever a sub-path is seen;
    the latest is its state.
    """
    spread = log.withWatermark("ts", idle).select("ts", F.explode(subpaths(F.col("path"))).alias("sub_path"))

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        f, seen, last = state.get if state.exists else (0.0, 0, None)
        times = np.sort(np.concatenate([x["ts"].to_numpy() for x in frames]))
        seconds = times.astype("datetime64[us]").astype(np.int64) / 1e6
        newest = max(seconds[-1], last if last is not None else seconds[-1])
        old = f * 0.5 ** ((newest - last) / half_life) if last is not None else 0.0
        f, seen = old + float((0.5 ** ((newest - seconds) / half_life)).sum()), seen + len(times)
        state.update((float(f), int(seen), float(newest)))
        state.setTimeoutTimestamp(int(newest * 1000) + _milliseconds(idle))
        yield pd.DataFrame({"sub_path": [str(key[0])], "f": [float(f)], "seen": [int(seen)], "last": [float(newest)]})

    return spread.groupBy("sub_path").applyInPandasWithState(step, STATE, "f double, seen long, last double", "update", GroupStateTimeout.EventTimeTimeout)


def _milliseconds(interval: str) -> int:
    number, unit = interval.split()
    return int(float(number) * {"second": 1, "minute": 60, "hour": 3600, "day": 86_400}[unit.rstrip("s")] * 1000)
