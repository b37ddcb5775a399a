from __future__ import annotations

import corpus_pipeline as P
from pyspark.sql import functions as F

from pathloom.llm import pieces
from pathloom.llm.near_dedup import near_duplicates
from pathloom.llm.registry import queries

from .helpers import SMALL, empty, hostile, near_components


def test_each_stage_takes_hard_documents(spark):
    for docs in (hostile(spark), empty(spark)):
        for name, stage in P.STAGES[:-1]:
            out = stage(spark, docs, SMALL)
            assert out.columns == docs.columns, name
            assert out.count() <= docs.count()
        assert P.pieces(spark, docs, SMALL).count() == docs.count()


def test_one_of_each_group_stays(spark):
    rows = [(r[0], r[1]) for r in hostile(spark).toDF(*"abcdefg").select("a", "b").collect()]
    kept = P.near_dedup(spark, hostile(spark), SMALL).toDF(*"abcdefg").filter("a is not null").select("a").collect()
    ids = [r[0] for r in kept]
    want = near_components({i: t for i, t in rows if i is not None})
    assert sorted(ids) == sorted(i for i, (_, c) in want.items() if i == c)


def test_stages_take_effect(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    for name, stage in P.STAGES[:-1]:
        out = P.stored(stage(spark, docs, SMALL), name)
        if name == "near_dedup":
            assert near_duplicates(out).filter("not kept").isEmpty()
        if name == "suffix_dedup":
            assert out.count() == docs.count()
            assert out.filter("n_chars <> length(text)").isEmpty()
            assert out.agg(F.sum("n_chars")).first()[0] < docs.agg(F.sum("n_chars")).first()[0]
        docs = out
    last = P.pieces(spark, docs, SMALL)
    back = {r["doc_id"]: r["text"] for r in pieces.decoded(last, P.public_tokenizers.path("piece_bpe_32k.model")).collect()}
    assert back == {r["doc_id"]: r["text"] for r in docs.collect()}


def test_registry_has_all():
    names = list(queries())
    assert names[-1] == "pipeline" and sorted(int(n[2:].split("_")[0]) for n in names[:-1]) == list(range(1, 11))
