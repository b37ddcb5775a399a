"""Registered queries: names, functions, and SQL that gives the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from pathloom.functions.workload import FIXED_30
from pathloom.plans.query import parse_path

# SQL of steps -------------------------------------------------------------------------------------

#: Each step's pairs in SQL; named types are numbered by the order of their names.
STEP_SQL = {
    "CO": "SELECT DISTINCT o_custkey AS s, o_orderkey AS d FROM orders",
    "OP": "SELECT DISTINCT l_orderkey AS s, l_partkey AS d FROM lineitem",
    "OS": "SELECT DISTINCT l_orderkey AS s, l_suppkey AS d FROM lineitem",
    "PS": "SELECT DISTINCT l_partkey AS s, l_suppkey AS d FROM lineitem",
    "CN": "SELECT CAST(c_custkey AS BIGINT) AS s, CAST(c_nationkey AS BIGINT) AS d FROM customer",
    "SN": "SELECT CAST(s_suppkey AS BIGINT) AS s, CAST(s_nationkey AS BIGINT) AS d FROM supplier",
    "NR": "SELECT CAST(n_nationkey AS BIGINT) AS s, CAST(n_regionkey AS BIGINT) AS d FROM nation",
    "PB": "SELECT p_partkey AS s, CAST(DENSE_RANK() OVER (ORDER BY p_brand) AS BIGINT) AS d FROM part",
    "PY": "SELECT p_partkey AS s, CAST(DENSE_RANK() OVER (ORDER BY p_type) AS BIGINT) AS d FROM part",
    "CG": "SELECT c_custkey AS s, CAST(DENSE_RANK() OVER (ORDER BY c_mktsegment) AS BIGINT) AS d FROM customer",
    "OM": "SELECT o_orderkey AS s, CAST(DENSE_RANK() OVER (ORDER BY DATE_TRUNC('month', o_orderdate)) AS BIGINT) AS d FROM orders",
    "UE": "SELECT user_id AS s, event_id AS d FROM events",
    "ET": "SELECT event_id AS s, CAST(DENSE_RANK() OVER (ORDER BY event_type) AS BIGINT) AS d FROM events",
    "EK": "SELECT event_id AS s, CAST(json_extract(props, '$.k') AS BIGINT) AS d FROM events",
    "ED": "SELECT event_id AS s, CAST(DENSE_RANK() OVER (ORDER BY DATE_TRUNC('day', ts)) AS BIGINT) AS d FROM events",
    "DL": "SELECT doc_id AS s, CAST(DENSE_RANK() OVER (ORDER BY lang) AS BIGINT) AS d FROM documents",
    "DZ": "SELECT doc_id AS s, CAST(DENSE_RANK() OVER (ORDER BY source) AS BIGINT) AS d FROM documents",
    "DQ": "SELECT DISTINCT doc_id AS s, CAST(quality AS BIGINT) AS d FROM labels",
    "DX": "SELECT DISTINCT doc_id AS s, CAST(toxic AS BIGINT) AS d FROM labels",
    "VA": "SELECT vec_id AS s, CAST(label AS BIGINT) AS d FROM embeddings",
    "next": "SELECT s, d FROM (SELECT o_orderkey AS s, LEAD(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS d FROM orders) z WHERE d IS NOT NULL",
}
#: Each type's keys and properties in SQL.
NODE_SQL = {
    "C": "SELECT c_custkey AS id, * FROM customer",
    "O": "SELECT o_orderkey AS id, * FROM orders",
    "P": "SELECT p_partkey AS id, * FROM part",
    "S": "SELECT s_suppkey AS id, * FROM supplier",
    "B": "SELECT DISTINCT CAST(DENSE_RANK() OVER (ORDER BY p_brand) AS BIGINT) AS id, p_brand FROM part",
    "N": "SELECT CAST(n_nationkey AS BIGINT) AS id, * FROM nation",
}


def step_sql(src: str, dst: str, name: str | None = None) -> str:
    if name:
        return STEP_SQL[name]
    if src + dst in STEP_SQL:
        return STEP_SQL[src + dst]
    return f"SELECT d AS s, s AS d FROM ({STEP_SQL[dst + src]}) r"


def path_sql(path: str, constraints: dict[int, str] | None = None, pairs: bool = True) -> str:
    """SQL of a metapath's result: all steps joined, paths counted."""
    q = parse_path(path, None, constraints)
    joins = [f"({step_sql(q.types[i], q.types[i + 1], q.edges[i])}) e{i}" for i in range(len(q) - 1)]
    on = [f"e{i}.d = e{i + 1}.s" for i in range(len(q) - 2)]
    for p, c in q.constraints:
        column = f"e{p}.s" if p < len(q) - 1 else f"e{p - 1}.d"
        on.append(f"{column} IN (SELECT id FROM ({NODE_SQL[q.types[p]]}) x WHERE {c})")
    where = f" WHERE {' AND '.join(on)}" if on else ""
    if not pairs:
        return f"FROM {', '.join(joins)}{where}"
    return f"SELECT e0.s AS src, e{len(q) - 2}.d AS dst, CAST(COUNT(*) AS BIGINT) AS n FROM {', '.join(joins)}{where} GROUP BY 1, 2"


def summary_sql(path: str, constraints: dict[int, str] | None = None) -> str:
    return f"SELECT CAST(COUNT(*) AS BIGINT) AS n_pairs, CAST(COALESCE(SUM(n), 0) AS BIGINT) AS sum_n, CAST(COALESCE(MAX(n), 0) AS BIGINT) AS max_n FROM ({path_sql(path, constraints)}) r"


FIXED_30_SQL = " UNION ALL ".join(f"SELECT {i} AS pos, * FROM ({summary_sql(path, {at: c})}) q{i}" for i, (_, path, at, c) in enumerate(FIXED_30))

# registry -----------------------------------------------------------------------------------------

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def register(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def rows_df(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def values_sql(rows: list[tuple], names: str) -> str:
    """SQL of a constant table, with the numbers' types as Spark has them."""

    def one(v) -> str:
        if v is None:
            return "NULL"
        if isinstance(v, bool):
            return str(v).upper()
        if isinstance(v, int):
            return f"CAST({v} AS BIGINT)"
        if isinstance(v, float):
            return f"CAST({v!r} AS DOUBLE)"
        return "'" + v.replace("'", "''") + "'"

    columns = names.split()
    parts = ["SELECT " + ", ".join(f"{one(v)} AS {c}" for v, c in zip(r, columns, strict=True)) for r in rows]
    return " UNION ALL ".join(parts)
