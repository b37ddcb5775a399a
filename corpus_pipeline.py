"""From raw documents to sampled token ids, in five stages.

Each stage takes (spark, docs, sf_dir) and gives a DataFrame, which is written as a table before the next one
reads it. Stages but the last give the columns of documents.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pathloom.llm.common import broadcast_if_small, pick, stored, table
from pathloom.llm.decontamination import leaked_items
from pathloom.llm.near_dedup import near_duplicates
from pathloom.llm.pieces import sampled_pieces
from pathloom.llm.quality import THRESHOLD, quality_scorer
from pathloom.llm.suffix_dedup import kept_text, repeated_spans

KEY, TEXT = "doc_id", "text"

#: SQL cannot express sampled segmentations, nearest neighbours or connected components.
ORACLE_SQL = None


def _plain(docs: DataFrame) -> tuple[DataFrame, Column, Column]:
    """docs with its columns named by place, and the key and text columns among them."""
    plain = docs.toDF(*(f"_{i}" for i in range(len(docs.columns))))
    at = docs.columns.index
    return plain, F.col(f"_{at(KEY)}"), F.col(f"_{at(TEXT)}")


def _without(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """The rows of docs whose key is not among ids."""
    plain, key, _ = _plain(docs)
    gone = stored(ids.toDF("gone").filter("gone is not null").distinct(), "gone")
    return plain.join(broadcast_if_small(gone, 16), key == F.col("gone"), "left_anti").toDF(*docs.columns)


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the nearest-neighbour classifier takes for good. Null and empty texts get the prior's verdict."""
    score = quality_scorer(docs, table(spark, sf_dir, "labels"), KEY, TEXT)
    plain, _, text = _plain(docs)
    return plain.filter(score(text) >= THRESHOLD).toDF(*docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: the one with the smallest id. Of rows that repeat id and text one stays."""
    found = near_duplicates(docs, KEY, TEXT)
    left = _without(docs, found.filter("not kept").select(KEY))
    plain, key, text = _plain(left)
    twice = plain.groupBy(key.alias("id")).count().filter("count > 1 and id is not null").select("id")
    if twice.isEmpty():
        return left
    again = plain.join(twice, key == F.col("id"), "left_semi").withColumn("_k", key).withColumn("_t", text).dropDuplicates(["_k", "_t"]).drop("_k", "_t")
    return plain.join(twice, key == F.col("id"), "left_anti").unionByName(again).toDF(*left.columns)


def suffix_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the bytes of strings that start earlier too; n_chars follows the text."""
    others = tuple(c for c in dict.fromkeys(docs.columns) if c not in (KEY, TEXT))
    out = repeated_spans(pick(docs, KEY, TEXT, *others), key=KEY, text=TEXT, carry=others)
    names = [KEY, TEXT, *others]
    plain = out.toDF(*(f"_{i}" for i in range(len(names))), *out.columns[len(names) :])
    new = F.when(F.col("n_removed") > 0, kept_text(F.col("_1"), F.col("starts"), F.col("sizes"))).otherwise(F.col("_1"))
    columns = {name: F.col(f"_{i}") for i, name in enumerate(names)} | {TEXT: F.col("_text")}
    if "n_chars" in others:
        kind = docs.schema["n_chars"].dataType
        columns["n_chars"] = F.when(F.col("n_removed") > 0, F.char_length("_text").cast(kind)).otherwise(columns["n_chars"])
    return plain.withColumn("_text", new).select(*(columns[c].alias(c) for c in dict.fromkeys(docs.columns)))


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents into which no benchmark item has leaked."""
    return _without(docs, leaked_items(docs, table(spark, sf_dir, "benchmark"), KEY, TEXT).select(KEY))


def pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_pieces, pieces: one sampled segmentation of each text, from which decoding gives the text back."""
    return sampled_pieces(docs, public_tokenizers.path("piece_bpe_32k.model"), key=KEY, text=TEXT, most_nodes=120_000)


STAGES = [("quality", quality), ("near_dedup", near_dedup), ("suffix_dedup", suffix_dedup), ("decontamination", decontamination), ("pieces", pieces)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stored(stage(spark, docs, sf_dir), name)
    return docs
