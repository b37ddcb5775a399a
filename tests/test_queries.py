"""Registered queries against their SQL on the smallest tables."""

from __future__ import annotations

import datetime
import decimal

import duckdb
import pytest

from pathloom import experiments as X
from pathloom import queries as Q

SMALL = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Each answers thirty queries over tables; test_metapaths compares engines on fewer, and their twins in memory run here.
LONG = {"engine_order_left", "engine_order_dense", "engine_traversal", "engine_final_cache", "engine_all_products", "engine_tree_lru", "engine_tree_size_cost", "engine_sparse"}


@pytest.fixture(autouse=True)
def _short_experiments(monkeypatch):
    monkeypatch.setattr(X, "WORKLOADS", 1)
    monkeypatch.setattr(X, "QUERIES", 60)
    monkeypatch.setattr(X, "ABLATION", 120)


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SMALL}/{t}.parquet')")
    return c


def plain(v):
    if isinstance(v, float):
        return round(v, 6)
    if isinstance(v, decimal.Decimal):
        return int(v)
    return v.replace(tzinfo=None) if isinstance(v, datetime.datetime) else v


@pytest.mark.parametrize("name", [n for n in Q.oracle_sql() if n not in LONG and n != "experiment_answers"])
def test_query_matches_sql(spark, duck, name):
    df = Q.queries()[name](spark, SMALL)
    columns = sorted(df.columns)
    got = sorted((tuple(plain(r[c]) for c in columns) for r in df.collect()), key=str)
    r = duck.execute(Q.oracle_sql()[name])
    names = [d[0] for d in r.description]
    assert sorted(names) == columns
    want = sorted((tuple(plain(x[names.index(c)]) for c in columns) for x in r.fetchall()), key=str)
    assert got == want


@pytest.mark.parametrize("name", [n for n in Q.queries() if n not in Q.oracle_sql()])
def test_query_without_sql_gives_rows(spark, name):
    assert Q.queries()[name](spark, SMALL).count() > 0


def test_engines_agree_over_generated_workloads(spark):
    rows = Q.queries()["experiment_answers"](spark, SMALL).collect()
    assert {(r["network"], r["queries"], r["differing"]) for r in rows} == {("commerce", 60, 0), ("activity", 60, 0)}


def test_entry_has_all_queries(spark):
    import __spark_entry__ as e

    assert set(Q.queries()) <= set(e.queries()) and set(e.oracle_sql()) <= set(e.queries())
    assert e.entry(spark).count() == 30
