"""Registered queries over the given tables, with SQL that gives the same rows."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from decimal import Decimal
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathloom import queries_workloads  # noqa: F401  registers its queries
from pathloom.functions.workload import FIXED_30, SubPaths, fixed_30, mine_constrained_overlaps, mine_overlaps, workload_df
from pathloom.operators import analytics as A
from pathloom.operators.backends import operand_stats
from pathloom.operators.engine import chain, engine, evaluate, evaluate_dense, evaluate_operands, evaluate_summary, instances, lower, run_uncached, traversal
from pathloom.operators.matrix import added, degree_profile, hinted, multiply, multiply_skewed, operations, sketch_entries, summary, transposed
from pathloom.plans.cost import CountSketch, MatrixStats, dense_cost, sketched, uniform_density, uniform_operations, uniform_product
from pathloom.plans.overlap import SubpathIndex
from pathloom.plans.planner import ChainPlanner, all_orders, order_cost
from pathloom.plans.policies import LruPolicy, SizeCostPolicy, dependency_policy
from pathloom.plans.query import key_text, parse_path
from pathloom.registry import FIXED_30_SQL, QUERIES, SQL, STEP_SQL, Query, path_sql, register, summary_sql, values_sql
from pathloom.registry import rows_df as _rows
from pathloom.sources.networks import EdgeType, TypedNetwork, activity, commerce, corpus, dictionary, vectors
from pathloom.sources.storage import bounded_column, fresh_path, read_edges, read_table, write_results
from pathloom.streaming.log import completed, overlap_counts, overlap_states, query_log_stream

#: Largest value of a long.
MOST_LONG = (1 << 63) - 1


def _path_query(net: Callable, path: str, constraints: dict[int, str] | None = None, planner: ChainPlanner | None = None) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        n = net(spark, sf)
        return evaluate(n, parse_path(path, n, constraints), planner)

    return run


#: Queries without constraints, by name.
PATHS = {
    "mqe_cop": (commerce, "C-O-P"), "mqe_pop": (commerce, "P-O-P"), "mqe_sos": (commerce, "S-O-S"), "mqe_copb": (commerce, "C-O-P-B"), "mqe_nco": (commerce, "N-C-O"),
    "mqe_ncopy": (commerce, "N-C-O-P-Y"), "mqe_bpsn": (commerce, "B-P-S-N"), "mqe_gcopb": (commerce, "G-C-O-P-B"), "mqe_rncop": (commerce, "R-N-C-O-P"),
    "mqe_copoc": (commerce, "C-O-P-O-C"), "mqe_uet": (activity, "U-E-T"), "mqe_uek": (activity, "U-E-K"), "mqe_uekeu": (activity, "U-E-K-E-U"), "mqe_ted": (activity, "T-E-D"),
    "mqe_lang_source": (corpus, "L-D-Z"), "mqe_quality_source": (corpus, "Q-D-Z"), "mqe_toxic_lang": (corpus, "X-D-L"), "mqe_vec_label": (vectors, "V-A-V"),
    "mqe_next_edge": (commerce, "C-O-[next]->O-P"), "mqe_reverse": (commerce, "P-O-C"),
}
for _name, (_net, _path) in PATHS.items():
    register(_name, path_sql(_path))(_path_query(_net, _path))


@register("mqe_psp", summary_sql("P-S-P"))
def mqe_psp(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    return evaluate_summary(n, parse_path("P-S-P", n))


#: Constrained queries, by name.
CONSTRAINED = {
    "mqe_c_date": ("C-O-P", {1: "o_orderdate>=DATE'2000-01-01'"}),
    "mqe_c_two_positions": ("C-O-P-O-C", {1: "o_orderdate>=DATE'2000-01-01'", 3: "o_orderdate>=DATE'2000-01-01'"}),
    "mqe_c_eq_first": ("C-O-P-O-C", {0: "C=7"}),
    "mqe_c_eq_last": ("P-O-C", {2: "C=7"}),
    "mqe_c_segment": ("N-C-O-P", {1: "c_mktsegment='BUILDING'"}),
    "mqe_c_in": ("C-O-P", {2: "p_brand IN ('Brand#1', 'Brand#7')"}),
    "mqe_c_like": ("C-O-P-B", {2: "p_type LIKE '%A%'"}),
    "mqe_c_null_safe": ("C-O-P", {0: "c_acctbal IS NOT NULL AND c_acctbal > 5000"}),
    "mqe_c_empty": ("C-O-P", {1: "o_totalprice < 0"}),
}
for _name, (_path, _c) in CONSTRAINED.items():
    register(_name, path_sql(_path, _c))(_path_query(commerce, _path, _c))


@register("mqe_c_type_level", path_sql("C-O-P-O-C", {1: "o_totalprice > 200000", 3: "o_totalprice > 200000"}))
def mqe_c_type_level(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    return evaluate(n, parse_path("C-O-P-O-C {O.o_totalprice > 200000}", n))


@register("mqe_multiplicity", "SELECT s AS src, d AS dst, CAST(SUM(n) AS BIGINT) AS n FROM (SELECT o_custkey AS s, l_partkey AS d, COUNT(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2) z GROUP BY 1, 2")
def mqe_multiplicity(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    n.weight = "multiplicity"
    return evaluate(n, parse_path("C-O-P", n))


@register("mqe_decimal", path_sql("C-O-P-B").replace("CAST(COUNT(*) AS BIGINT)", "CAST(COUNT(*) AS DECIMAL(38,0))"))
def mqe_decimal(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    return evaluate(n, parse_path("C-O-P-B", n), decimal=True)


@register("mqe_labelled", f"SELECT src, n_name AS src_name, dst, dst_name, n FROM ({path_sql('N-C-O-P-Y')}) r JOIN nation ON src = n_nationkey JOIN (SELECT DISTINCT CAST(DENSE_RANK() OVER (ORDER BY p_type) AS BIGINT) AS id, p_type AS dst_name FROM part) y ON dst = y.id")
def mqe_labelled(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    q = parse_path("N-C-O-P-Y", n)
    return A.labelled(evaluate(n, q), n, q)


@register("instances_cop", f"SELECT e0.s AS v0, e0.d AS v1, e1.d AS v2 {path_sql('C-O-P', {0: 'C=7'}, pairs=False)}")
def instances_cop(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    return instances(n, parse_path("C-O-P", n, {0: "C=7"})).select("v0", "v1", "v2")


# plans --------------------------------------------------------------------------------------------

for _kind in ("left", "right", "dense", "sparse"):
    register(f"plan_{_kind}", path_sql("G-C-O-P-B", {2: "o_orderdate>=DATE'2001-01-01'"}))(_path_query(commerce, "G-C-O-P-B", {2: "o_orderdate>=DATE'2001-01-01'"}, ChainPlanner(_kind)))


def _sketched_stats(net, q) -> list:
    """Sizes of a query's steps with entries per node, collected once per step: the costlier estimator, for networks whose node counts fit on the driver.

    A predicate's share scales the counts, as it does the uniform estimate."""
    out = []
    for i, stats in enumerate(operand_stats(net, q)):
        sides = []
        for side, t in (("src", q.types[i]), ("dst", q.types[i + 1])):
            key = ("sketch", q.types[i], q.types[i + 1], q.edges[i], side)
            if key not in net.counted:
                x = net.adjacency(q.types[i], q.types[i + 1], q.edges[i])
                ids = net.nodes[t].df.select("id")
                counts = ids.join(x.groupBy(F.col(side).alias("id")).count(), "id", "left").orderBy("id").select(F.coalesce("count", F.lit(0)).cast("double").alias("c"))
                net.counted[key] = bounded_column(counts)
            sides.append(net.counted[key])
        whole = sides[0].sum()
        share = stats.nnz / whole if whole else 0.0
        out.append(MatrixStats(stats.rows, stats.cols, stats.nnz, CountSketch(sides[0] * share, sides[1] * share)))
    return out


@register("plan_sketch", path_sql("N-C-O-P"))
def plan_sketch(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    q = parse_path("N-C-O-P", n)
    plan = ChainPlanner("sparse", product=sketched).plan(_sketched_stats(n, q))
    return lower(n, q, plan)


for _name, _f in (("operand", evaluate_operands), ("folded", evaluate)):

    def _selected(spark: SparkSession, sf: str, f=_f) -> DataFrame:
        n = commerce(spark, sf)
        return f(n, parse_path("G-C-O-P-B", n, {1: "c_acctbal>5000", 2: "o_orderdate>=DATE'2001-01-01'"}))

    register(f"plan_sel_{_name}", path_sql("G-C-O-P-B", {1: "c_acctbal>5000", 2: "o_orderdate>=DATE'2001-01-01'"}))(_selected)

_PLACES = "(SELECT COUNT(*) FROM customer) AS c, (SELECT COUNT(*) FROM orders) AS o, (SELECT COUNT(*) FROM part) AS p"


@register(
    "selection_placement",
    f"SELECT placed, CAST(ops AS BIGINT) AS ops, ops = MIN(ops) OVER () AS chosen FROM (SELECT 'left' AS placed, c * o * o + c * o * p AS ops FROM (SELECT {_PLACES}) t UNION ALL SELECT 'right' AS placed, o * o * p + c * o * p AS ops FROM (SELECT {_PLACES}) t) x",
)
def selection_placement(spark: SparkSession, sf: str) -> DataFrame:
    """Dense operations of C-O-P with a predicate on O, by the side to which the selection is multiplied, and which one the planner chooses."""
    n = commerce(spark, sf)
    _, stats = chain(n, parse_path("C-O-P", n, {1: "o_orderdate>=DATE'2001-01-01'"}))
    planner = ChainPlanner("dense")
    order = planner.plan(stats).order()
    found = [(name, int(order_cost(o, stats, planner)[0]), order == text) for name, o, text in (("left", (((0, 1), (1, 2)), (2, 3)), "((01 12) 23)"), ("right", ((0, 1), ((1, 2), (2, 3))), "(01 (12 23))"))]
    return _rows(spark, found, "placed string, ops long, chosen boolean")


_MET = "(SELECT COUNT(DISTINCT o_custkey) FROM orders) AS c, (SELECT COUNT(DISTINCT l_orderkey) FROM lineitem) AS o, (SELECT COUNT(DISTINCT l_partkey) FROM lineitem) AS p, (SELECT COUNT(DISTINCT p_brand) FROM part) AS b"


@register(
    "dense_ops_example",
    f"SELECT 'left' AS plan, CAST(c * o * p + c * p * b AS BIGINT) AS ops FROM (SELECT {_MET}) t UNION ALL SELECT 'right' AS plan, CAST(o * p * b + c * o * b AS BIGINT) AS ops FROM (SELECT {_MET}) t",
)
def dense_ops_example(spark: SparkSession, sf: str) -> DataFrame:
    """Dense operations of C-O-P-B from the left and from the right, over the nodes that orders and their lines name.

    ops is a long while both fit in one, else a decimal: a product of three counts outgrows 64 bits from millions of nodes on.
    """
    many = lambda t, column: read_table(spark, sf, t).agg(F.count_distinct(column)).first()[0]
    c, o, p, b = many("orders", "o_custkey"), many("lineitem", "l_orderkey"), many("lineitem", "l_partkey"), many("part", "p_brand")
    left, right = dense_cost(c, o, p) + dense_cost(c, p, b), dense_cost(o, p, b) + dense_cost(c, o, b)
    if max(left, right) > MOST_LONG:
        return _rows(spark, [("left", Decimal(left)), ("right", Decimal(right))], "plan string, ops decimal(38,0)")
    return _rows(spark, [("left", int(left)), ("right", int(right))], "plan string, ops long")


for _kind in ("dense", "sparse"):

    def _dp_cost(spark: SparkSession, sf: str, kind: str = _kind) -> DataFrame:
        """length, agrees: the dynamic program against all orders."""
        n, rows = commerce(spark, sf), []
        for path in ("C-O-P-B", "N-C-O-P-Y", "G-C-O-P-S-N"):
            stats, planner = operand_stats(n, parse_path(path, n)), ChainPlanner(kind)
            least = min(order_cost(o, stats, planner)[0] for o in all_orders(0, len(stats)))
            rows.append((len(stats) + 1, abs(planner.plan(stats).cost - least) <= 1e-9 * max(1.0, least)))
        return _rows(spark, rows, "length int, agrees boolean")

    register(f"dp_cost_{_kind}", "SELECT * FROM (VALUES (4, TRUE), (5, TRUE), (6, TRUE)) t(length, agrees)")(_dp_cost)


@register("nop_exact", f"SELECT CAST(SUM(a.n * b.n) AS BIGINT) AS n_op FROM (SELECT d AS k, COUNT(*) AS n FROM ({STEP_SQL['CO']}) x GROUP BY 1) a JOIN (SELECT s AS k, COUNT(*) AS n FROM ({STEP_SQL['OP']}) y GROUP BY 1) b ON a.k = b.k")
def nop_exact(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    return operations(n.adjacency("C", "O"), n.adjacency("O", "P"))


_COUNTS = "(SELECT COUNT(*) FROM customer) AS c, (SELECT COUNT(*) FROM orders) AS o, (SELECT COUNT(*) FROM part) AS p, (SELECT COUNT(*) FROM (" + STEP_SQL["CO"] + ") z) AS co, (SELECT COUNT(*) FROM (" + STEP_SQL["OP"] + ") z) AS op"


@register("density_uniform", f"SELECT ROUND(1 - POWER(1 - (CAST(co AS DOUBLE) / (c * o)) * (CAST(op AS DOUBLE) / (o * p)), o), 9) AS density, ROUND(CAST(co AS DOUBLE) * op / o, 3) AS n_op FROM (SELECT {_COUNTS}) t")
def density_uniform(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    x, y = n.step_stats("C", "O", exact=True), n.step_stats("O", "P", exact=True)
    return _rows(spark, [(round(uniform_density(x.density, y.density, x.cols), 9), round(uniform_operations(x, y), 3))], "density double, n_op double")


@register("degree_hist", f"SELECT degree, CAST(COUNT(*) AS BIGINT) AS nodes FROM (SELECT s, CAST(COUNT(*) AS BIGINT) AS degree FROM ({STEP_SQL['CO']}) x GROUP BY 1) y GROUP BY 1")
def degree_hist(spark: SparkSession, sf: str) -> DataFrame:
    return degree_profile(commerce(spark, sf).adjacency("C", "O"))


def _estimates_sql(a: str, b: str, m: str, n: str, k: str) -> str:
    """One product's exact, uniform and sketched entries and scalar products, from its steps' SQL and its node tables."""
    x, y = (STEP_SQL[t] if t in STEP_SQL else f"SELECT d AS s, s AS d FROM ({STEP_SQL[t[::-1]]}) r" for t in (a, b))
    return f"""
SELECT '{a[0]}-{a[1]}-{b[1]}' AS product, nnz, ROUND(m * k * (1 - POWER(1 - (nx / (m * n)) * (ny / (n * k)), n)), 1) AS uniform_nnz,
  ROUND(CASE WHEN rx <= 1 OR cy <= 1 THEN met ELSE cells * (1 - EXP(empty)) END, 1) AS sketch_nnz, n_op, ROUND(nx * ny / n, 1) AS uniform_n_op
FROM (SELECT CAST((SELECT COUNT(*) FROM {m}) AS DOUBLE) AS m, CAST((SELECT COUNT(*) FROM {n}) AS DOUBLE) AS n, CAST((SELECT COUNT(*) FROM {k}) AS DOUBLE) AS k,
  CAST((SELECT COUNT(*) FROM ({x}) u) AS DOUBLE) AS nx, CAST((SELECT COUNT(*) FROM ({y}) u) AS DOUBLE) AS ny,
  (SELECT CAST(COUNT(*) AS BIGINT) FROM (SELECT DISTINCT u.s, v.d FROM ({x}) u JOIN ({y}) v ON u.d = v.s) w) AS nnz,
  (SELECT MAX(c) FROM (SELECT COUNT(*) AS c FROM ({x}) u GROUP BY s) w) AS rx, (SELECT MAX(c) FROM (SELECT COUNT(*) AS c FROM ({y}) u GROUP BY d) w) AS cy) sizes,
 (SELECT CAST(SUM(i * o) AS BIGINT) AS n_op, CAST(SUM(i * o) AS DOUBLE) AS met, SUM(LN(1 - CAST(i * o AS DOUBLE) / cells)) AS empty, MAX(cells) AS cells
  FROM (SELECT d AS k, COUNT(*) AS i FROM ({x}) u GROUP BY 1) p JOIN (SELECT s AS k, COUNT(*) AS o FROM ({y}) u GROUP BY 1) q ON p.k = q.k,
  (SELECT CAST((SELECT COUNT(DISTINCT s) FROM ({x}) u) AS DOUBLE) * (SELECT COUNT(DISTINCT d) FROM ({y}) u) AS cells) z) sums"""


_ESTIMATED = (("CO", "OP", "customer", "orders", "part"), ("PO", "OP", "part", "orders", "part"), ("SO", "OS", "supplier", "orders", "supplier"), ("OP", "PS", "orders", "part", "supplier"))


@register("estimate_errors", " UNION ALL ".join(f"SELECT * FROM ({_estimates_sql(*p)}) e{i}" for i, p in enumerate(_ESTIMATED)))
def estimate_errors(spark: SparkSession, sf: str) -> DataFrame:
    """Entries and scalar products of some products against the uniform and the sketched estimate."""
    n, parts = commerce(spark, sf), []
    for a, b, *_ in _ESTIMATED:
        x, y = n.adjacency(*a), n.adjacency(*b)
        sx, sy = n.step_stats(*a, exact=True), n.step_stats(*b, exact=True)
        exact = multiply(x, y).agg(F.count("*").alias("nnz"))
        guess = _rows(spark, [(f"{a[0]}-{a[1]}-{b[1]}", round(uniform_product(sx, sy).nnz, 1), round(uniform_operations(sx, sy), 1))], "product string, uniform_nnz double, uniform_n_op double")
        parts.append(guess.join(exact).join(operations(x, y)).join(sketch_entries(x, y).select(F.round("sketch_nnz", 1).alias("sketch_nnz"))))
    return reduce(DataFrame.unionByName, parts)


@register("density_sketch", f"SELECT ROUND(sketch_nnz, 0) AS sketch_nnz FROM ({_estimates_sql(*_ESTIMATED[1])}) e")
def density_sketch(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    return sketch_entries(n.adjacency("P", "O"), n.adjacency("O", "P")).select(F.round("sketch_nnz", 0).alias("sketch_nnz"))


@register("nop_uniform", f"SELECT uniform_n_op AS n_op FROM ({_estimates_sql(*_ESTIMATED[0])}) e")
def nop_uniform(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    return _rows(spark, [(round(uniform_operations(n.step_stats("C", "O", exact=True), n.step_stats("O", "P", exact=True)), 1),)], "n_op double")


@register("multiply_skewed", path_sql("S-O-S"))
def multiply_skewed_query(spark: SparkSession, sf: str) -> DataFrame:
    """A product whose hot middle nodes are spread over cells."""
    n = commerce(spark, sf)
    return multiply_skewed(n.adjacency("S", "O"), n.adjacency("O", "S"), heavy=16)


@register("multiply_dealt", path_sql("P-S-P"))
def multiply_dealt(spark: SparkSession, sf: str) -> DataFrame:
    """A product of few middle nodes, dealt by its scalar products."""
    n = commerce(spark, sf)
    x, y = n.adjacency("P", "S"), n.adjacency("S", "P")
    return multiply(x, y, operations=max(1e8, uniform_operations(n.step_stats("P", "S"), n.step_stats("S", "P"))), middle=n.size("S"))


# engines ------------------------------------------------------------------------------------------

for _kind in ("sparse", "left", "dense", "traversal"):

    def _uncached(spark: SparkSession, sf: str, kind: str = _kind) -> DataFrame:
        n = commerce(spark, sf, keep=True)
        return run_uncached(n, fixed_30(n), kind)

    register({"traversal": "engine_traversal", "sparse": "engine_sparse"}.get(_kind, f"engine_order_{_kind}"), FIXED_30_SQL)(_uncached)

for _name in ("final_cache", "all_products", "tree_lru", "tree_size_cost", "reference"):

    def _cached(spark: SparkSession, sf: str, name: str = _name) -> DataFrame:
        n = commerce(spark, sf, keep=True)
        return engine(n, name).run(fixed_30(n))

    register(f"engine_{_name}", FIXED_30_SQL)(_cached)


@register("engine_dense", path_sql("B-P-S-N"))
def engine_dense(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    return evaluate_dense(n, parse_path("B-P-S-N", n))


@register("engine_traversal_pairs", path_sql("N-C-O-P"))
def engine_traversal_pairs(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    return traversal(n, parse_path("N-C-O-P", n))


# overlaps and caches ------------------------------------------------------------------------------



def _log(spark: SparkSession, sf: str) -> DataFrame:
    """Events as a query log: each event type stands for a path."""
    e = read_table(spark, sf, "events")
    return e.select(F.col("ts").cast("timestamp").alias("ts"), F.when(F.col("event_type").isin("view", "click"), "U-E-T").otherwise("U-E-K").alias("path"))


def _constrained_log(spark: SparkSession, sf: str) -> DataFrame:
    """(event_type, k, path, constraints) of all events: those that ask for keys do so for one group of ten keys."""
    e = read_table(spark, sf, "events").select("event_type", F.get_json_object("props", "$.k").cast("long").alias("k"))
    asks = ~F.col("event_type").isin("view", "click")
    group = F.concat(F.lit("K="), (F.col("k") % 10).cast("string"))
    constraints = F.when(asks, F.create_map(F.lit(2), group)).otherwise(F.create_map().cast("map<int,string>"))
    return e.select("event_type", "k", F.when(asks, "U-E-K").otherwise("U-E-T").alias("path"), constraints.alias("constraints"))


def _event_index(spark: SparkSession, sf: str) -> SubpathIndex:
    """The overlap index of a log of one query for each pair of an event type and a key; the pairs are as few as those names."""
    index = SubpathIndex()
    kinds = _constrained_log(spark, sf).dropDuplicates(["event_type", "k"]).orderBy("event_type", "k")
    for r in kinds.collect():
        index.insert(parse_path(r["path"], None, r["constraints"]))
    return index


_KINDS_SQL = "SELECT event_type, CASE WHEN event_type IN ('view', 'click') THEN 'U-E-T' ELSE 'U-E-K' END AS path, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events"
_PATH_COUNTS_SQL = f"SELECT COUNT(*) AS n, COUNT(*) FILTER (WHERE path = 'U-E-T') AS t, COUNT(*) FILTER (WHERE path = 'U-E-K') AS k FROM (SELECT DISTINCT * FROM ({_KINDS_SQL}) z) y"
#: What is seen of the sub-paths of both paths: each one's count, which has a node of its own if continuations differ.
_NODES = (("U-E", "n"), ("E", "n"), ("U-E-T", "t"), ("E-T", "t"), ("T", "t"), ("U-E-K", "k"), ("E-K", "k"), ("K", "k"))


@register("overlap_nodes", " UNION ALL ".join(f"SELECT '{p}' AS sub_path, {c} AS f FROM ({_PATH_COUNTS_SQL}) x" for p, c in _NODES))
def overlap_nodes(spark: SparkSession, sf: str) -> DataFrame:
    return _rows(spark, [("-".join(path), x.f) for path, x in _event_index(spark, sf).internal()], "sub_path string, f long")


@register("overlap_space", f"WITH c AS ({_PATH_COUNTS_SQL}), g AS (SELECT COUNT(DISTINCT k % 10) AS g FROM ({_KINDS_SQL}) z WHERE path = 'U-E-K') SELECT 3 * n AS leaves, CAST(8 AS BIGINT) AS internal, 6 * n - 1 AS bound, 32 * (3 * n + 8) + 8 * (3 * n + 8) + 48 * (5 + 3 * g + 3 * n) AS bytes FROM c, g")
def overlap_space(spark: SparkSession, sf: str) -> DataFrame:
    r = _event_index(spark, sf).space_report()
    return _rows(spark, [(r["leaves"], r["internal"], r["bound"], r["bytes"])], "leaves long, internal long, bound long, bytes long")


_SUBPATHS_SQL = "SELECT 'U-E' AS sub_path FROM events UNION ALL SELECT CASE WHEN event_type IN ('view', 'click') THEN 'E-T' ELSE 'E-K' END FROM events UNION ALL SELECT CASE WHEN event_type IN ('view', 'click') THEN 'U-E-T' ELSE 'U-E-K' END FROM events"


@register("overlap_freq", f"SELECT sub_path, CAST(COUNT(*) AS BIGINT) AS f FROM ({_SUBPATHS_SQL}) x GROUP BY 1 HAVING COUNT(*) >= 2")
def overlap_freq(spark: SparkSession, sf: str) -> DataFrame:
    return mine_overlaps(_log(spark, sf))


@register("overlap_constrained", f"SELECT 'E-K' AS sub_path, '1:id = ' || CAST(k % 10 AS VARCHAR) AS ckey, CAST(COUNT(*) AS BIGINT) AS f FROM (SELECT DISTINCT * FROM ({_KINDS_SQL}) z) y WHERE path = 'U-E-K' GROUP BY 2")
def overlap_constrained(spark: SparkSession, sf: str) -> DataFrame:
    node = _event_index(spark, sf).find(("E", "K"))
    rows = sorted(("E-K", key_text(k), f) for k, f in node.keys.items())
    return _rows(spark, rows, "sub_path string, ckey string, f long")


#: Event types as requests for sub-paths, by what each costs to make from nothing. U-E-T and U-E-K can be made from U-E.
_ASKED_PATHS = {"view": ("U-E", 4), "click": ("U-E-T", 6), "purchase": ("U-E-K", 8), "signup": ("E-K", 5), "error": ("E-D", 3)}
_FROM = ("U-E", ("U-E-T", "U-E-K"))


def _trace_sql(dependent: bool) -> str:
    """Each user's requests and hits: a recursion over the user's events, its state the two stored items, the older first, and the level of inflation.

    An item has its key k, frequency f, base b, cost c and, from dependent costs, what was taken off (t)."""
    base, made = _FROM[0], ", ".join(f"'{k}'" for k in _FROM[1])
    names = " ".join(f"WHEN '{t}' THEN '{k}'" for t, (k, _) in _ASKED_PATHS.items())
    costs = " ".join(f"WHEN '{t}' THEN {c}" for t, (_, c) in _ASKED_PATHS.items())
    both = str(dependent).upper()
    less = f"CASE WHEN {both} AND k IN ({made}) AND (k1 = '{base}' OR k2 = '{base}') THEN {_ASKED_PATHS['view'][1]} ELSE 0 END"
    #: what stays in the first place: the item that is not evicted
    stays = lambda x: f"CASE WHEN k2 IS NULL THEN {x}1 WHEN first THEN {x}2 ELSE {x}1 END"
    back = f"{both} AND gone = '{base}' AND rk IN ({made})"
    taken = f"{both} AND k = '{base}' AND rk IN ({made})"
    return f"""WITH RECURSIVE e AS (SELECT CAST(user_id AS BIGINT) AS user_id, CASE event_type {names} END AS k, CAST(CASE event_type {costs} END AS DOUBLE) AS cost,
 ROW_NUMBER() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS i, CAST(ROW_NUMBER() OVER (PARTITION BY user_id, event_type ORDER BY ts, event_id) AS DOUBLE) AS f FROM events),
s AS (
 SELECT DISTINCT user_id, CAST(0 AS BIGINT) AS i, FALSE AS hit, CAST(0 AS DOUBLE) AS level, CAST(NULL AS VARCHAR) AS k1, CAST(NULL AS DOUBLE) AS f1, CAST(NULL AS DOUBLE) AS b1, CAST(NULL AS DOUBLE) AS c1, CAST(NULL AS DOUBLE) AS t1,
  CAST(NULL AS VARCHAR) AS k2, CAST(NULL AS DOUBLE) AS f2, CAST(NULL AS DOUBLE) AS b2, CAST(NULL AS DOUBLE) AS c2, CAST(NULL AS DOUBLE) AS t2 FROM e
 UNION ALL
 SELECT user_id, i, hit, CASE WHEN miss THEN up ELSE level END,
  CASE WHEN hit OR rk IS NOT NULL THEN rk ELSE k END, CASE WHEN k1 = k OR rk IS NULL THEN f ELSE rf END, CASE WHEN k1 = k THEN level WHEN rk IS NULL THEN up ELSE rb END,
  CASE WHEN hit THEN c1 WHEN rk IS NULL THEN price WHEN {taken} THEN rc - LEAST(rc, price) ELSE rc END, CASE WHEN hit THEN t1 WHEN rk IS NULL THEN NULL WHEN {taken} THEN LEAST(rc, price) ELSE rt END,
  CASE WHEN hit THEN k2 WHEN rk IS NULL THEN NULL ELSE k END, CASE WHEN hit AND k2 = k THEN f WHEN hit THEN f2 WHEN rk IS NULL THEN NULL ELSE f END, CASE WHEN hit AND k2 = k THEN level WHEN hit THEN b2 WHEN rk IS NULL THEN NULL ELSE up END,
  CASE WHEN hit THEN c2 WHEN rk IS NULL THEN NULL ELSE price END, CASE WHEN hit THEN t2 ELSE NULL END
 FROM (SELECT *, CASE WHEN {back} THEN r0c + COALESCE(r0t, gc) ELSE r0c END AS rc, CASE WHEN {back} THEN NULL ELSE r0t END AS rt FROM (
  SELECT *, CASE WHEN hit THEN k1 ELSE {stays('k')} END AS rk, CASE WHEN hit THEN f1 ELSE {stays('f')} END AS rf, CASE WHEN hit THEN b1 ELSE {stays('b')} END AS rb, {stays('c')} AS r0c, {stays('t')} AS r0t,
   CASE WHEN miss THEN CASE WHEN first THEN k1 ELSE k2 END END AS gone, CASE WHEN first THEN c1 ELSE c2 END AS gc, CASE WHEN miss THEN LEAST(u1, u2) ELSE level END AS up FROM (
   SELECT *, NOT hit AND k2 IS NOT NULL AS miss, u1 <= u2 AS first FROM (
    SELECT s.user_id, e.i, e.k, e.f, COALESCE(k1 = k OR k2 = k, FALSE) AS hit, level, k1, f1, b1, c1, t1, k2, f2, b2, c2, t2, f1 * c1 + b1 AS u1, f2 * c2 + b2 AS u2, cost - {less} AS price
    FROM s JOIN e ON e.user_id = s.user_id AND e.i = s.i + 1) a) b) c) d)
SELECT user_id, CAST(COUNT(*) AS BIGINT) AS requests, CAST(COUNT(*) FILTER (WHERE hit) AS BIGINT) AS hits FROM s WHERE i > 0 GROUP BY 1"""


def _asked_by_user(spark: SparkSession, sf: str, make: Callable, hit: Callable) -> DataFrame:
    """Each user's requests and hits: make() gives a user's cache, hit(cache, event type) asks it. A user's events pass one after the other."""
    asked = read_table(spark, sf, "events").select(F.col("user_id").cast("long").alias("user_id"), "event_type", "ts", "event_id")
    asked = asked.repartition("user_id").sortWithinPartitions("user_id", "ts", "event_id").select("user_id", "event_type")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = []  # user, requests, hits; the last user's may go on in the next batch
        cache = None
        for batch in batches:
            for user, kind in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if cache is None or user != found[-1][0]:
                    cache = make()
                    found.append([user, 0, 0])
                found[-1][1] += 1
                found[-1][2] += hit(cache, kind)
            yield _counted(found[:-1])
            found = found[-1:]
        yield _counted(found)

    def _counted(rows: list[list]) -> pa.RecordBatch:
        columns = zip(*rows, strict=True) if rows else ([], [], [])
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["user_id", "requests", "hits"])

    return asked.mapInArrow(run, "user_id long, requests long, hits long")


def _trace_hit(policy: SizeCostPolicy, event_type: str) -> bool:
    """Asks for an event type's sub-path; what can be made from a stored item costs what is left to make."""
    key, cost = _ASKED_PATHS[event_type]
    stored = policy.ancestors and key in _FROM[1] and _FROM[0] in policy
    return policy.request(key, float(cost - _ASKED_PATHS["view"][1] * bool(stored)), 1).hit


_TRACES = {
    "size_cost": lambda: SizeCostPolicy(2),
    "dependency": lambda: dependency_policy(2, lambda k: [_FROM[0]] if k in _FROM[1] else []),
}
for _name, _make in _TRACES.items():

    def _cache_trace(spark: SparkSession, sf: str, make: Callable = _make) -> DataFrame:
        """Each user's events as requests for sub-paths to a cache of that user that holds two."""
        return _asked_by_user(spark, sf, make, _trace_hit)

    register(f"cache_{_name}_trace", _trace_sql(_name == "dependency"))(_cache_trace)


_ASKED_SQL = "SELECT user_id, event_type, ROW_NUMBER() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS i FROM events"


@register(
    "cache_lru_trace",
    f"""WITH e AS ({_ASKED_SQL}), p AS (SELECT *, LAG(i) OVER (PARTITION BY user_id, event_type ORDER BY i) AS before FROM e),
between AS (SELECT p.user_id, p.i, p.before, COUNT(DISTINCT b.event_type) AS others FROM p LEFT JOIN e b ON b.user_id = p.user_id AND b.i > p.before AND b.i < p.i GROUP BY 1, 2, 3)
SELECT CAST(user_id AS BIGINT) AS user_id, CAST(COUNT(*) AS BIGINT) AS requests, CAST(COUNT(*) FILTER (WHERE before IS NOT NULL AND others < 2) AS BIGINT) AS hits FROM between GROUP BY 1""",
)
def cache_lru_trace(spark: SparkSession, sf: str) -> DataFrame:
    """Each user's events as requests for their types to a cache of that user that holds two."""
    return _asked_by_user(spark, sf, lambda: LruPolicy(2), lambda p, k: p.request(k, 1, 1).hit)


_BRAND_LINES = "SELECT p_brand AS item, COUNT(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1"


@register("cache_oversize", f"SELECT item, n <= 0.8 * (1.25 * AVG(n) OVER ()) AS stored FROM ({_BRAND_LINES}) x")
def cache_oversize(spark: SparkSession, sf: str) -> DataFrame:
    """Which brands' lines a cache takes whose largest share is as many as a brand has on average."""
    part, li = read_table(spark, sf, "part"), read_table(spark, sf, "lineitem")
    lines = li.join(part, F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").count().orderBy("p_brand").collect()  # brands, not lines
    p = LruPolicy(1.25 * sum(r["count"] for r in lines) / max(1, len(lines)), 0.8)
    return _rows(spark, [(r["p_brand"], p.request(r["p_brand"], 1, r["count"]).stored) for r in lines], "item string, stored boolean")


# workloads and networks ---------------------------------------------------------------------------

_TYPE_EDGES = " UNION ALL ".join(f"SELECT '{a}' AS a, '{b}' AS b" for s in STEP_SQL if len(s) == 2 and s[0] not in "UEDV" for a, b in (s, s[::-1]))
for _length in (3, 4, 5):
    _joins = ", ".join(f"({_TYPE_EDGES}) t{i}" for i in range(_length - 1))
    _on = " AND ".join(f"t{i}.b = t{i + 1}.a" for i in range(_length - 2))
    _text = " || '-' || ".join(["t0.a", *(f"t{i}.b" for i in range(_length - 1))])
    register(f"workload_schema_paths_{_length}", f"SELECT {_text} AS path FROM {_joins} WHERE {_on}")(lambda spark, sf, length=_length: commerce(spark, sf).schema_paths(length))


for _percent in (60, 80, 100):

    def _split(spark: SparkSession, sf: str, percent: int = _percent) -> DataFrame:
        n = commerce(spark, sf).core_split("O", percent)
        return summary(evaluate(n, parse_path("C-O-P", n)))

    register(f"core_split_{_percent}", summary_sql("C-O-P", {1: f"id % 100 < {_percent}"}))(_split)

_STATS = [("C-O", "CO"), ("O-P", "OP"), ("O-S", "OS"), ("P-S", "PS"), ("C-N", "CN"), ("S-N", "SN"), ("N-R", "NR"), ("P-B", "PB"), ("P-Y", "PY"), ("C-G", "CG"), ("O-M", "OM"), ("next", "next")]


@register("net_stats", " UNION ALL ".join(f"SELECT '{n}' AS name, CAST(COUNT(*) AS BIGINT) AS n FROM (SELECT DISTINCT s, d FROM ({STEP_SQL[k]}) a) x" for n, k in _STATS))
def net_stats(spark: SparkSession, sf: str) -> DataFrame:
    return commerce(spark, sf).stats().filter("kind = 'edge'").select("name", "n")


@register("net_schema", " UNION ALL ".join(f"SELECT '{n[0] if '-' in n else 'O'}' AS src_type, '{n}' AS edge_type, '{n[-1] if '-' in n else 'O'}' AS dst_type, CAST(COUNT(*) AS BIGINT) AS n_edges FROM (SELECT DISTINCT s, d FROM ({STEP_SQL[k]}) a) x" for n, k in _STATS))
def net_schema(spark: SparkSession, sf: str) -> DataFrame:
    return commerce(spark, sf).infer_schema()


@register("sql_surface", f"SELECT CAST(COUNT(*) AS BIGINT) AS n_pairs, CAST(SUM(n) AS BIGINT) AS sum_n FROM ({path_sql('C-O-P-B')}) r WHERE n > 1")
def sql_surface(spark: SparkSession, sf: str) -> DataFrame:
    """A metapath's result as a view for SQL."""
    A.define(commerce(spark, sf), "customers_and_brands", "C-O-P-B")
    return spark.sql("SELECT COUNT(*) AS n_pairs, SUM(n) AS sum_n FROM customers_and_brands WHERE n > 1")


# uses of results ----------------------------------------------------------------------------------

_SOS, _SPS = path_sql("S-O-S"), path_sql("S-P-S")


def _pairs(spark: SparkSession, sf: str, path: str) -> DataFrame:
    n = commerce(spark, sf)
    return evaluate(n, parse_path(path, n))


@register("similarity_topk", f"SELECT src, dst, score, rank FROM (SELECT src, dst, CAST(n AS DOUBLE) AS score, CAST(ROW_NUMBER() OVER (PARTITION BY src ORDER BY n DESC, dst) AS INTEGER) AS rank FROM ({_SOS}) r WHERE src <> dst) z WHERE rank <= 5")
def similarity_topk(spark: SparkSession, sf: str) -> DataFrame:
    return A.path_similarity(_pairs(spark, sf, "S-O-S"), 5)


@register("similarity_normalized", f"WITH r AS ({_SOS}), o AS (SELECT src AS id, n AS own FROM r WHERE src = dst) SELECT src, dst, score, rank FROM (SELECT r.src, r.dst, 2.0 * CAST(r.n AS DOUBLE) / (a.own + b.own) AS score, CAST(ROW_NUMBER() OVER (PARTITION BY r.src ORDER BY 2.0 * CAST(r.n AS DOUBLE) / (a.own + b.own) DESC, r.dst) AS INTEGER) AS rank FROM r JOIN o a ON r.src = a.id JOIN o b ON r.dst = b.id WHERE r.src <> r.dst) z WHERE rank <= 5")
def similarity_normalized(spark: SparkSession, sf: str) -> DataFrame:
    return A.path_similarity(_pairs(spark, sf, "S-O-S"), 5, "normalized")


@register("rank_centrality")
def rank_centrality(spark: SparkSession, sf: str) -> DataFrame:
    return A.path_rank(_pairs(spark, sf, "B-P-B"), iterations=3)


@register("features_pivot", f"SELECT src, dst, CAST(COALESCE(SUM(CASE WHEN k = 'orders' THEN n END), 0) AS BIGINT) AS orders, CAST(COALESCE(SUM(CASE WHEN k = 'parts' THEN n END), 0) AS BIGINT) AS parts FROM (SELECT 'orders' AS k, * FROM ({_SOS}) a UNION ALL SELECT 'parts' AS k, * FROM ({_SPS}) b) z GROUP BY 1, 2")
def features_pivot(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    return A.path_features(n, {"orders": parse_path("S-O-S", n), "parts": parse_path("S-P-S", n)})


for _name, _f, _op in (("intersect", A.pairs_both, "INTERSECT"), ("union", A.pairs_either, "UNION"), ("except", A.pairs_minus, "EXCEPT")):
    _a, _b = path_sql("C-O-P", {1: "o_totalprice > 100000"}), path_sql("C-O-P", {2: "p_size > 25"})

    def _sets(spark: SparkSession, sf: str, f=_f) -> DataFrame:
        n = commerce(spark, sf)
        return f(evaluate(n, parse_path("C-O-P", n, {1: "o_totalprice > 100000"})), evaluate(n, parse_path("C-O-P", n, {2: "p_size > 25"})))

    register(f"pairs_{_name}", f"SELECT src, dst FROM ({_a}) a {_op} SELECT src, dst FROM ({_b}) b")(_sets)


@register("pairs_anti", f"SELECT o_orderkey AS id FROM orders WHERE o_orderkey NOT IN (SELECT src FROM ({path_sql('O-P-B')}) r)")
def pairs_anti(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    return A.unreached(n, parse_path("O-P-B", n))


@register("topk_per_source", f"SELECT src, dst, n, rank FROM (SELECT *, CAST(ROW_NUMBER() OVER (PARTITION BY src ORDER BY n DESC, dst) AS INTEGER) AS rank FROM ({path_sql('C-O-P-B')}) r) z WHERE rank <= 3")
def topk_per_source(spark: SparkSession, sf: str) -> DataFrame:
    return A.top_k_per_source(_pairs(spark, sf, "C-O-P-B"), 3)


@register("semiring_boolean", f"SELECT DISTINCT src, dst, CAST(1 AS BIGINT) AS n FROM ({path_sql('C-O-P')}) r")
def semiring_boolean(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    return multiply(n.adjacency("C", "O"), n.adjacency("O", "P"), "reach")


@register("semiring_shortest", f"SELECT DISTINCT src, dst, CAST(2 AS BIGINT) AS n FROM ({path_sql('C-O-P')}) r")
def semiring_shortest(spark: SparkSession, sf: str) -> DataFrame:
    n = commerce(spark, sf)
    return multiply(n.adjacency("C", "O"), n.adjacency("O", "P"), "shortest")


@register("transposed_product", path_sql("P-O-C"))
def transposed_product(spark: SparkSession, sf: str) -> DataFrame:
    return transposed(_pairs(spark, sf, "C-O-P"))


@register("edge_delta", path_sql("C-O-P"))
def edge_delta(spark: SparkSession, sf: str) -> DataFrame:
    """A result kept up to date: the product over old edges plus the product over appended ones."""
    n = commerce(spark, sf)
    x, y = n.adjacency("C", "O"), n.adjacency("O", "P")
    return added(multiply(x.filter("dst % 10 <> 0"), y), multiply(x.filter("dst % 10 = 0"), y))


@register("range_join_window", "SELECT a.o_custkey AS custkey, CAST(COUNT(*) AS BIGINT) AS n FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND b.o_orderdate > a.o_orderdate AND b.o_orderdate <= a.o_orderdate + INTERVAL 90 DAY GROUP BY 1")
def range_join_window(spark: SparkSession, sf: str) -> DataFrame:
    """Pairs of a customer's orders within 90 days: equal keys and a range."""
    o = read_table(spark, sf, "orders").select("o_custkey", "o_orderdate")
    b = o.select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("later"))
    near = o.join(b, (F.col("o_custkey") == F.col("k")) & (F.col("later") > F.col("o_orderdate")) & (F.col("later") <= F.col("o_orderdate") + F.expr("INTERVAL 90 DAYS")))
    return near.groupBy(F.col("o_custkey").alias("custkey")).agg(F.count("*").alias("n"))


@register("asof_next", "SELECT o_orderkey AS id, LEAD(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS following FROM orders")
def asof_next(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return read_table(spark, sf, "orders").select(F.col("o_orderkey").alias("id"), F.lead("o_orderkey").over(w).alias("following"))


@register("json_props", "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, CAST(COUNT(*) AS BIGINT) AS n FROM events GROUP BY 1")
def json_props(spark: SparkSession, sf: str) -> DataFrame:
    return read_table(spark, sf, "events").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n"))


# streams ------------------------------------------------------------------------------------------

_PAIRS_SQL = "SELECT ts, x AS sub_path FROM (SELECT ts, CASE WHEN event_type IN ('view', 'click') THEN 'E-T' ELSE 'E-K' END AS x FROM events UNION ALL SELECT ts, 'U-E' AS x FROM events UNION ALL SELECT ts, CASE WHEN event_type IN ('view', 'click') THEN 'U-E-T' ELSE 'U-E-K' END AS x FROM events) z"


@register("stream_tumbling", f"SELECT sub_path, CAST(DATE_TRUNC('day', ts) AS TIMESTAMP) AS start, CAST(COUNT(*) AS BIGINT) AS f FROM ({_PAIRS_SQL}) q GROUP BY 1, 2")
def stream_tumbling(spark: SparkSession, sf: str) -> DataFrame:
    return overlap_counts(_log(spark, sf), "1 day").withColumn("start", F.col("start").cast("timestamp_ntz"))


@register("stream_sliding", f"SELECT sub_path, start, CAST(COUNT(*) AS BIGINT) AS f FROM (SELECT sub_path, CAST(DATE_TRUNC('day', ts) AS TIMESTAMP) AS start FROM ({_PAIRS_SQL}) a UNION ALL SELECT sub_path, CAST(DATE_TRUNC('day', ts) AS TIMESTAMP) - INTERVAL 1 DAY AS start FROM ({_PAIRS_SQL}) b) q GROUP BY 1, 2")
def stream_sliding(spark: SparkSession, sf: str) -> DataFrame:
    return overlap_counts(_log(spark, sf), "2 days", slide="1 day").withColumn("start", F.col("start").cast("timestamp_ntz"))


@register("stream_session_windows", f"SELECT sub_path, MIN(ts) AS start, CAST(COUNT(*) AS BIGINT) AS f FROM (SELECT sub_path, ts, SUM(fresh) OVER (PARTITION BY sub_path ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM (SELECT sub_path, ts, CASE WHEN ts <= LAG(ts) OVER (PARTITION BY sub_path ORDER BY ts) + INTERVAL 10 MINUTE THEN 0 ELSE 1 END AS fresh FROM ({_PAIRS_SQL}) q) x) y GROUP BY sub_path, session")
def stream_session_windows(spark: SparkSession, sf: str) -> DataFrame:
    return overlap_counts(_log(spark, sf), "", gap="10 minutes").withColumn("start", F.col("start").cast("timestamp_ntz"))


_TUMBLING_SQL = SQL["stream_tumbling"]


@register("stream_batch_equivalence", _TUMBLING_SQL)
def stream_batch_equivalence(spark: SparkSession, sf: str) -> DataFrame:
    """The tumbling counts from a stream that has read all there is."""
    found = completed(overlap_counts(query_log_stream(spark, sf), "1 day"))
    return found.withColumn("start", F.col("start").cast("timestamp_ntz"))


@register("stream_late", _TUMBLING_SQL)
def stream_late(spark: SparkSession, sf: str) -> DataFrame:
    """The tumbling counts of a stream that gets every event again a year too late: the watermark drops those."""
    base = fresh_path(spark, "late")
    log = _log(spark, sf)
    log.coalesce(1).write.parquet(f"{base}/log")
    counts = overlap_counts(spark.readStream.schema(log.schema).parquet(f"{base}/log"), "1 day")

    def batch(df: DataFrame, number: int) -> None:
        df.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{base}/out/part{number}")

    run = counts.writeStream.outputMode("update").foreachBatch(batch).option("checkpointLocation", f"{base}/state").start()
    try:
        run.processAllAvailable()
        log.withColumn("ts", F.col("ts") - F.expr("INTERVAL 365 DAYS")).coalesce(1).write.mode("append").parquet(f"{base}/log")
        run.processAllAvailable()
    finally:
        run.stop()
    out = spark.read.option("recursiveFileLookup", True).parquet(f"{base}/out")
    latest = out.groupBy("sub_path", "start").agg(F.max_by("f", "batch").alias("f"))
    return latest.withColumn("start", F.col("start").cast("timestamp_ntz"))


@register("stream_states", f"SELECT sub_path, CAST(COUNT(*) AS BIGINT) AS seen, ROUND(SUM(POWER(0.5, (EPOCH(top) - EPOCH(ts)) / 86400.0)), 6) AS f FROM (SELECT *, MAX(ts) OVER (PARTITION BY sub_path) AS top FROM ({_PAIRS_SQL}) q) x GROUP BY 1")
def stream_states(spark: SparkSession, sf: str) -> DataFrame:
    """Decayed frequencies kept as a stream's state."""
    out = completed(overlap_states(query_log_stream(spark, sf)), "update")
    return out.groupBy("sub_path").agg(F.max_by("seen", "batch").alias("seen"), F.round(F.max_by("f", "batch"), 6).alias("f"))


# more operators on results ------------------------------------------------------------------------


@register("pairs_semi", f"SELECT c_custkey AS id FROM customer WHERE c_custkey IN (SELECT src FROM ({path_sql('C-O-P', {2: 'p_size > 45'})}) r)")
def pairs_semi(spark: SparkSession, sf: str) -> DataFrame:
    """Customers from whom some path starts."""
    n = commerce(spark, sf)
    return A.reached(n, parse_path("C-O-P", n, {2: "p_size > 45"}))


@register("approx_distinct", f"SELECT src, ABS(COUNT(DISTINCT dst) - COUNT(DISTINCT dst)) <= 1 AS close FROM ({path_sql('B-P-S')}) r GROUP BY 1")
def approx_distinct(spark: SparkSession, sf: str) -> DataFrame:
    """Is the approximate number of nodes reached within a tenth of the exact one."""
    pairs = _pairs(spark, sf, "B-P-S")
    return pairs.groupBy("src").agg((F.abs(F.approx_count_distinct("dst", 0.02) - F.count_distinct("dst")) <= 0.1 * F.count_distinct("dst")).alias("close"))


@register("topk_global", f"SELECT src, dst, n FROM ({path_sql('C-O-P-B')}) r ORDER BY n DESC, src, dst LIMIT 25")
def topk_global(spark: SparkSession, sf: str) -> DataFrame:
    return A.top_k(_pairs(spark, sf, "C-O-P-B"), 25)


@register("semiring_bottleneck", "SELECT o_custkey AS src, l_partkey AS dst, CAST(MAX(LEAST(x, q)) AS BIGINT) AS n FROM (SELECT o_custkey, o_orderkey, MAX(CAST(ROUND(o_totalprice) AS BIGINT)) AS x FROM orders GROUP BY 1, 2) o JOIN (SELECT l_orderkey, l_partkey, MAX(CAST(l_quantity AS BIGINT) * 1000) AS q FROM lineitem GROUP BY 1, 2) l ON o_orderkey = l_orderkey GROUP BY 1, 2")
def semiring_bottleneck(spark: SparkSession, sf: str) -> DataFrame:
    """The widest path between customers and parts, its width the least of its edges' weights."""
    o, li = read_table(spark, sf, "orders"), read_table(spark, sf, "lineitem")
    x = o.groupBy(F.col("o_custkey").alias("src"), F.col("o_orderkey").alias("dst")).agg(F.max(F.round("o_totalprice").cast("long")).alias("n"))
    y = li.groupBy(F.col("l_orderkey").alias("src"), F.col("l_partkey").alias("dst")).agg(F.max(F.col("l_quantity").cast("long") * 1000).alias("n"))
    return multiply(x, y, "bottleneck")


for _hint in ("merge", "shuffle_hash", "broadcast"):

    def _hinted(spark: SparkSession, sf: str, hint: str = _hint) -> DataFrame:
        """A product whose join is of a named kind; a side too large to be sent to every executor is shuffled."""
        n = commerce(spark, sf)
        return multiply(n.adjacency("C", "O"), hinted(n.adjacency("O", "P"), hint, n.step_stats("O", "P").nnz))

    register(f"join_{_hint}", path_sql("C-O-P"))(_hinted)


@register("features_by_month", "SELECT s AS src, CAST(EXTRACT(YEAR FROM m) AS INTEGER) AS year, CAST(COUNT(*) AS BIGINT) AS n FROM (SELECT o_custkey AS s, DATE_TRUNC('month', o_orderdate) AS m FROM orders) x GROUP BY 1, 2")
def features_by_month(spark: SparkSession, sf: str) -> DataFrame:
    """A metapath's result by a date part of its end nodes' names."""
    n = commerce(spark, sf)
    found = evaluate(n, parse_path("C-O-M", n)).join(n.nodes["M"].df.select(F.col("id").alias("dst"), F.year("name").alias("year")), "dst")
    return found.groupBy("src", "year").agg(F.sum("n").alias("n"))


@register("rank_windows", f"SELECT src, dst, n, CAST(RANK() OVER (PARTITION BY src ORDER BY n DESC) AS INTEGER) AS rank, CAST(DENSE_RANK() OVER (PARTITION BY src ORDER BY n DESC) AS INTEGER) AS level, CAST(SUM(n) OVER (PARTITION BY src ORDER BY n DESC RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS running FROM ({path_sql('N-C-O-P-Y')}) r")
def rank_windows(spark: SparkSession, sf: str) -> DataFrame:
    """Ranks of pairs and the running sum over a range frame."""
    w = Window.partitionBy("src").orderBy(F.desc("n"))
    return _pairs(spark, sf, "N-C-O-P-Y").select(
        "src", "dst", "n", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("level"), F.sum("n").over(w.rangeBetween(Window.unboundedPreceding, 0)).alias("running")
    )


@register("overlap_mined", f"SELECT 'E-K' AS sub_path, '1:K=' || CAST(k % 10 AS VARCHAR) AS ckey, CAST(COUNT(*) AS BIGINT) AS f FROM ({_KINDS_SQL}) x WHERE path = 'U-E-K' GROUP BY 2 HAVING COUNT(*) >= 2")
def overlap_mined(spark: SparkSession, sf: str) -> DataFrame:
    """Overlaps by constraint from a log of any size: one sub-path's, over all events."""
    return mine_constrained_overlaps(_constrained_log(spark, sf)).filter("sub_path = 'E-K'").select("sub_path", "ckey", "f")


@register("overlap_maximal", f"SELECT sub_path FROM ({_SUBPATHS_SQL}) x GROUP BY 1 HAVING COUNT(*) >= 2")
def overlap_maximal(spark: SparkSession, sf: str) -> DataFrame:
    """The mined sub-paths that the overlap index has a node for."""
    log = _log(spark, sf).select("path", F.create_map().cast("map<int,string>").alias("constraints"))
    return mine_constrained_overlaps(log).filter("maximal").select("sub_path").distinct()


@register("sql_subpaths", f"SELECT p.path, sub_path, start, length, n FROM (SELECT path, COUNT(*) AS n FROM ({_KINDS_SQL}) z GROUP BY 1) p JOIN ({values_sql([(f'U-E-{x}', *row) for x in 'TK' for row in (('U-E', 0, 2), (f'U-E-{x}', 0, 3), (f'E-{x}', 1, 2))], 'path sub_path start length')}) s ON p.path = s.path")
def sql_subpaths(spark: SparkSession, sf: str) -> DataFrame:
    """Sub-paths of the events' paths, and how many events have the path, from a table function in SQL."""
    spark.udtf.register("sub_paths", SubPaths)
    _log(spark, sf).groupBy("path").agg(F.count("*").alias("n")).createOrReplaceTempView("event_paths")
    return spark.sql("SELECT path, sub_path, CAST(start AS BIGINT) AS start, CAST(length AS BIGINT) AS length, n FROM event_paths, LATERAL sub_paths(path)")


@register("sql_metapath", path_sql("C-O-P-B", {0: "id = 7"}))
def sql_metapath(spark: SparkSession, sf: str) -> DataFrame:
    """A metapath called from SQL text, with its constraint as a parameter."""
    return A.metapath_sql(spark, commerce(spark, sf), "SELECT src, dst, n FROM metapath('C-O-P-B {C.id = 7}')")


@register("edge_invalidation", path_sql("C-O-P-B"))
def edge_invalidation(spark: SparkSession, sf: str) -> DataFrame:
    """An engine whose network gets edges appended: stored results that used the relation go, the answer is the new one's."""
    n = commerce(spark, sf)
    orders = next(e for e in n.edges if e.name == "C-O")
    some = EdgeType("C-O", "C", "O", orders.df.filter("dst % 10 <> 0"), True)
    before = TypedNetwork(n.name, spark, n.nodes, [some if e.name == "C-O" else e for e in n.edges])
    e = engine(before, "reference")
    q = parse_path("C-O-P-B", before)
    e.run_one(q)
    e.run_one(parse_path("O-P-B", before))
    e.invalidate("C-O", before.with_appended("C-O", orders.df.filter("dst % 10 = 0")))
    return e.run_one(q)


@register("edge_files", path_sql("C-O-P"))
def edge_files(spark: SparkSession, sf: str) -> DataFrame:
    """A network whose relations come from ORC and CSV files."""
    n, base = commerce(spark, sf), fresh_path(spark, "edges")
    write_results(n.edges[0].df, f"{base}/co", kind="orc")
    write_results(n.edges[1].df, f"{base}/op", kind="csv")
    edges = [EdgeType("C-O", "C", "O", read_edges(spark, f"{base}/co", "orc")), EdgeType("O-P", "O", "P", read_edges(spark, f"{base}/op", "csv", header=False))]
    net = TypedNetwork("files", spark, {t: n.nodes[t] for t in "COP"}, edges)
    return evaluate(net, parse_path("C-O-P", net))


@register("dictionary_large", "SELECT CAST(DENSE_RANK() OVER (ORDER BY p_name) AS BIGINT) AS id, p_name AS name FROM (SELECT DISTINCT p_name FROM part) p")
def dictionary_large(spark: SparkSession, sf: str) -> DataFrame:
    """Names numbered by ranges, as for domains too large for one task."""
    return dictionary(read_table(spark, sf, "part").select("p_name"), large=True)


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
