"""Connected components over DataFrames, by contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored

#: Times a round follows the chain of smaller neighbours, each time twice as far.
DOUBLINGS = 3


def components(edges: DataFrame) -> DataFrame:
    """(node, component) for the nodes of edges (a, b): the smallest node reachable.

    Each round hangs every node under its smallest smaller neighbour (partially aggregated, so a hub's
    edges are reduced where they lie), follows those chains, and contracts: edges go between the nodes hung
    on, and those within one are gone. So rounds get smaller, and the loop ends when no edge is left.
    Rounds are tables in the shared folder. Self-edges and repeated edges do no harm.
    """
    rest = stored(_proper(edges), "cc-edges")
    labels = edges.select(F.col("a").alias("node")).union(edges.select("b")).distinct().withColumn("component", F.col("node"))
    while not rest.isEmpty():
        up = rest.groupBy(F.col("b").alias("node")).agg(F.min("a").alias("to"))
        for _ in range(DOUBLINGS):
            further = up.select(F.col("node").alias("to"), F.col("to").alias("top"))
            up = up.join(further, "to", "left").select("node", F.coalesce("top", "to").alias("to"))
        up = stored(up, "cc-up")
        labels = stored(_moved(labels, "component", up), "cc-labels")
        rest = stored(_proper(_moved(_moved(rest, "a", up), "b", up)), "cc-edges")
    return labels


def _proper(edges: DataFrame) -> DataFrame:
    return edges.filter("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def _moved(df: DataFrame, column: str, up: DataFrame) -> DataFrame:
    """df with the nodes of a column replaced by those they hang under."""
    others = [c for c in df.columns if c != column]
    moved = df.join(up.select(F.col("node").alias(column), "to"), column, "left")
    return moved.select(*others, F.coalesce("to", column).alias(column))
