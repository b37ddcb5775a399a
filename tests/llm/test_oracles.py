from __future__ import annotations

import duckdb
import pytest

from pathloom.llm.oracles import SQL
from pathloom.llm.registry import queries

from .helpers import SMALL


@pytest.mark.parametrize("name", list(SQL))
def test_operator_matches_sql(spark, name):
    c = duckdb.connect()
    c.execute(f"CREATE VIEW documents AS SELECT * FROM read_parquet('{SMALL}/documents.parquet')")
    df = queries()[name](spark, SMALL)
    r = c.execute(SQL[name])
    names = [d[0] for d in r.description]
    assert sorted(names) == sorted(df.columns)
    want = sorted(str([x[names.index(k)] for k in df.columns]) for x in r.fetchall())
    assert sorted(str(list(x)) for x in df.collect()) == want
