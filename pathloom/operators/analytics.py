"""What is done with metapath results: similarity, ranking, features, and sets of pairs."""

from __future__ import annotations

import re
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathloom.plans.query import PathQuery, parse_path
from pathloom.sources.networks import TypedNetwork
from pathloom.sources.storage import stored

from .engine import evaluate


def top_k_per_source(pairs: DataFrame, k: int) -> DataFrame:
    """The k strongest pairs of each source; ties go to the smaller dst."""
    w = Window.partitionBy("src").orderBy(F.desc("n"), "dst")
    return pairs.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def top_k(pairs: DataFrame, k: int) -> DataFrame:
    """The k strongest pairs of all; ties go to the smaller src, then dst."""
    return pairs.select("src", "dst", "n").orderBy(F.desc("n"), "src", "dst").limit(k)


def path_similarity(pairs: DataFrame, k: int = 10, measure: str = "shared") -> DataFrame:
    """src, dst, score, rank over a symmetric path's result: shared paths, or normalised by both nodes' own."""
    if measure == "shared":
        scored = pairs.filter("src <> dst").select("src", "dst", F.col("n").cast("double").alias("score"))
    else:
        own = pairs.filter("src = dst").select(F.col("src").alias("id"), F.col("n").alias("own"))
        both = pairs.filter("src <> dst").join(own.select(F.col("id").alias("src"), F.col("own").alias("a")), "src").join(own.select(F.col("id").alias("dst"), F.col("own").alias("b")), "dst")
        scored = both.select("src", "dst", (2.0 * F.col("n") / (F.col("a") + F.col("b"))).alias("score"))
    w = Window.partitionBy("src").orderBy(F.desc("score"), "dst")
    return scored.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def path_rank(pairs: DataFrame, damping: float = 0.85, iterations: int = 10) -> DataFrame:
    """id, score: centrality in the network whose edges are a path's pairs. Rounds are cut by tables."""
    out = stored(pairs.groupBy("src").agg(F.sum("n").alias("total")), "rank-out")
    moves = stored(pairs.join(out, "src").select("src", "dst", (F.col("n") / F.col("total")).alias("p")), "rank-moves")
    nodes = stored(pairs.select(F.col("src").alias("id")).union(pairs.select("dst")).distinct(), "rank-nodes")
    n = nodes.count()
    scores = nodes.withColumn("score", F.lit(1.0 / max(n, 1)))
    for _ in range(iterations):
        into = moves.join(scores.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("p") * F.col("score")).alias("got"))
        scores = stored(nodes.join(into, "id", "left").select("id", (F.lit((1 - damping) / max(n, 1)) + damping * F.coalesce("got", F.lit(0.0))).alias("score")), "rank")
    return scores


def path_features(net: TypedNetwork, queries: dict[str, PathQuery]) -> DataFrame:
    """src, dst and a column of counts for each named path between the same types; 0 where a path has no instance."""
    parts = [evaluate(net, q).select("src", "dst", F.lit(name).alias("path"), "n") for name, q in queries.items()]
    return reduce(DataFrame.unionByName, parts).groupBy("src", "dst").pivot("path", list(queries)).agg(F.sum("n")).na.fill(0)


def pairs_both(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("src", "dst").intersect(b.select("src", "dst"))


def pairs_either(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("src", "dst").union(b.select("src", "dst")).distinct()


def pairs_minus(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("src", "dst").subtract(b.select("src", "dst"))


def unreached(net: TypedNetwork, q: PathQuery) -> DataFrame:
    """id: nodes of the first type from which no instance of the path starts."""
    return net.nodes[q.types[0]].df.select("id").join(evaluate(net, q).select(F.col("src").alias("id")).distinct(), "id", "left_anti")


def reached(net: TypedNetwork, q: PathQuery) -> DataFrame:
    """id: nodes of the first type from which some instance of the path starts."""
    return net.nodes[q.types[0]].df.select("id").join(evaluate(net, q).select(F.col("src").alias("id")), "id", "left_semi")


def labelled(result: DataFrame, net: TypedNetwork, q: PathQuery) -> DataFrame:
    """A result with the names of its end nodes."""
    for side, t in (("src", q.types[0]), ("dst", q.types[-1])):
        node = net.nodes[t]
        result = result.join(node.df.select(F.col("id").alias(side), F.col(node.label).cast("string").alias(f"{side}_name")), side)
    return result.select("src", "src_name", "dst", "dst_name", "n")


def define(net: TypedNetwork, view: str, path: str, constraints: dict[int, str] | None = None) -> None:
    """A metapath's result (src, dst, n) as a temporary view, computed when SQL reads it."""
    evaluate(net, parse_path(path, net, constraints)).createOrReplaceTempView(view)


_CALL = re.compile(r"metapath\s*\(\s*'((?:[^']|'')*)'\s*\)", re.IGNORECASE)


def metapath_sql(spark: SparkSession, net: TypedNetwork, text: str) -> DataFrame:
    """SQL in which metapath('C-O-P {O.o_totalprice > 5}') stands for a path's result (src, dst, n), planned when the statement is."""
    args = {}

    def named(m: re.Match) -> str:
        name = f"path{len(args)}"
        args[name] = evaluate(net, parse_path(m[1].replace("''", "'"), net))
        return "{" + name + "}"

    return spark.sql(_CALL.sub(named, text), **args)
