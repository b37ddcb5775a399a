"""Registered queries over workloads: engines, their measures, and the experiments."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathloom import experiments as X
from pathloom.functions import workload as W
from pathloom.operators.backends import SharedTableBackend, SharedTables
from pathloom.operators.engine import CACHES, TraversalEngine, engine, evaluate, evaluate_dense, run_uncached
from pathloom.operators.matrix import summary
from pathloom.operators.memory import MemoryBackend, Remembered, TooLarge, in_memory
from pathloom.plans.cost import fit_coefficients
from pathloom.plans.overlap import built, infixes
from pathloom.plans.planner import ChainPlanner
from pathloom.plans.query import parse_path
from pathloom.registry import FIXED_30_SQL, STEP_SQL, Query, register, rows_df, values_sql
from pathloom.sources.networks import activity, commerce
from pathloom.sources.storage import METRICS_SCHEMA

#: Nodes, and edges, up to which the fixed workload is answered over arrays on the driver.
MOST_ROWS = 14_000_000

# engines ------------------------------------------------------------------------------------------

for _kind in ("sparse", "left", "dense", "traversal"):

    def _uncached(spark: SparkSession, sf: str, kind: str = _kind) -> DataFrame:
        n = commerce(spark, sf, keep=True)
        return run_uncached(n, W.fixed_30(n), kind)

    register({"traversal": "engine_traversal", "sparse": "engine_sparse"}.get(_kind, f"engine_order_{_kind}"), FIXED_30_SQL)(_uncached)

for _name in ("final_cache", "all_products", "tree_lru", "tree_size_cost", "reference"):

    def _cached(spark: SparkSession, sf: str, name: str = _name) -> DataFrame:
        n = commerce(spark, sf, keep=True)
        return engine(n, name).run(W.fixed_30(n))

    register(f"engine_{_name}", FIXED_30_SQL)(_cached)


@register("cache_second_level", FIXED_30_SQL)
def cache_second_level(spark: SparkSession, sf: str) -> DataFrame:
    """The reference engine with a cache of two kilobytes, whose evicted tables stay and are read again."""
    n = commerce(spark, sf, keep=True)
    return engine(n, "reference", capacity=2048, second_level=True).run(W.fixed_30(n))


#: Ways to run the reference engine that differ from its defaults; answers do not.
VARIANTS = {
    "reverse": {"reuse_reverse": True},
    "subsumed": {"reuse_subsumed": True},
    "nearest_prefix": {"nearest": True},
    "any_substring": {"ancestors": infixes},
    "pattern_frequency": {"freq_scope": "pattern"},
    "unaware_index": {"freq_scope": "pattern", "constraint_aware": False},
    "measured_cost": {"cost_measure": "measured"},
    "restricted_steps": {"cache_restricted": True},
    "horizon": {"horizon": 5},
    "no_substitution": {"substitute": "none"},
    "cached_substitution": {"substitute": "cached"},
}


def _fixed(spark: SparkSession, sf: str, repeats: int = 1, shared: SharedTables | None = None) -> tuple[Callable, list]:
    """What makes engines over the fixed workload, and its queries: over arrays that are read once, or over tables where they are too large.

    Over arrays, and over tables that are shared, a product of the same two matrices is made once for all engines.
    """
    n = commerce(spark, sf)
    queries = W.fixed_30(n) * repeats
    try:
        net = in_memory(n, queries, MOST_ROWS, used=True)
    except TooLarge:
        n = commerce(spark, sf, keep=True)
        if shared:
            return lambda name, capacity, **options: engine(n, name, capacity, backend=SharedTableBackend(n, shared), clock=shared.clock, **options), queries
        return lambda name, capacity, **options: engine(n, name, capacity, **options), queries
    known = Remembered()
    return lambda name, capacity, **options: engine(net, name, capacity, backend=MemoryBackend(net, known), clock=known.clock, **options), queries


def _answered(spark: SparkSession, sf: str, name: str, capacity: float, **options):
    """An engine over the fixed workload, and its answers."""
    make, queries = _fixed(spark, sf)
    e = make(name, capacity, **options)
    return e, [(i, *e.summary_of(q, i)) for i, q in enumerate(queries)]


for _name, _options in VARIANTS.items():

    def _variant(spark: SparkSession, sf: str, options: dict = _options) -> DataFrame:
        return rows_df(spark, _answered(spark, sf, "reference", 200_000, **options)[1], "pos int, n_pairs long, sum_n long, max_n long")

    register(f"engine_{_name}", FIXED_30_SQL)(_variant)

# measures over engines' runs ----------------------------------------------------------------------

_QUERIES = W.fixed_30()
#: The fixed workload with what an engine without a cache, and one that keeps all results, make of each query.
_MADE_SQL = f"""SELECT engine, CAST(pos AS INTEGER) AS pos, CAST(CASE WHEN engine = 'sparse' OR again = 1 THEN width - 2 ELSE 0 END AS INTEGER) AS products,
 CAST(CASE WHEN engine = 'final_cache' AND again > 1 THEN 1 ELSE 0 END AS INTEGER) AS cached_spans, CAST(CASE WHEN engine = 'final_cache' AND again = 1 THEN 1 ELSE 0 END AS INTEGER) AS offers
FROM (SELECT *, ROW_NUMBER() OVER (PARTITION BY path, place, predicate ORDER BY pos) AS again FROM ({values_sql([(i, q.path, len(q), *q.constraints[0]) for i, q in enumerate(_QUERIES + _QUERIES)], "pos path width place predicate")}) w),
 (SELECT 'sparse' AS engine UNION ALL SELECT 'final_cache' AS engine) e"""


def _made(spark: SparkSession, sf: str) -> DataFrame:
    """What two engines did over the fixed workload, asked twice."""
    parts = []
    make, queries = _fixed(spark, sf, repeats=2)
    for name in ("sparse", "final_cache"):
        e = make(name, 1e15)
        for i, q in enumerate(queries):
            e.summary_of(q, i)
        parts.append(spark.createDataFrame([(name, m.pos, m.products, m.cached_spans, m.offers) for m in e.metrics], "engine string, pos int, products int, cached_spans int, offers int"))
    return X.union(parts)


@register("engine_metrics", _MADE_SQL)
def engine_metrics(spark: SparkSession, sf: str) -> DataFrame:
    return _made(spark, sf)


@register("engine_metrics_all")
def engine_metrics_all(spark: SparkSession, sf: str) -> DataFrame:
    """All that every engine notes of each query of the fixed workload, with a cache that evicts."""
    shared = SharedTables()
    make, queries = _fixed(spark, sf, shared=shared)
    engines = [make(name, 20_000) for name in CACHES]
    try:
        for i, q in enumerate(queries):
            for e in engines:
                e.summary_of(q, i)
            shared.trim()
    finally:
        shared.close()
    return X.union([spark.createDataFrame([tuple(vars(m).values()) for m in e.metrics], METRICS_SCHEMA) for e in engines])


@register("engine_catalog")
def engine_catalog(spark: SparkSession, sf: str) -> DataFrame:
    """The spans that the reference engine stored over the fixed workload, and those it evicted."""
    e, _ = _answered(spark, sf, "reference", 20_000)
    e.net = commerce(spark, sf)
    return e.catalog()


@register("metrics_cumulative", f"SELECT *, CAST(SUM(products) OVER (PARTITION BY engine ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS running FROM ({_MADE_SQL}) m")
def metrics_cumulative(spark: SparkSession, sf: str) -> DataFrame:
    return W.cumulative(_made(spark, sf), "products")


@register("metrics_quartiles", f"SELECT engine, QUANTILE_CONT(products, 0.25) AS q1, QUANTILE_CONT(products, 0.5) AS q2, QUANTILE_CONT(products, 0.75) AS q3 FROM ({_MADE_SQL}) m GROUP BY 1")
def metrics_quartiles(spark: SparkSession, sf: str) -> DataFrame:
    return W.quartiles(_made(spark, sf), "products")


@register("metrics_improvement", f"WITH m AS (SELECT engine, AVG(products) AS mean FROM ({_MADE_SQL}) x GROUP BY 1) SELECT engine, mean, 1 - mean / (SELECT mean FROM m WHERE engine = 'sparse') AS improvement FROM m")
def metrics_improvement(spark: SparkSession, sf: str) -> DataFrame:
    return W.improvement(_made(spark, sf), "sparse", "products")


@register("metrics_rollup", f"SELECT engine, CAST(pos % 2 AS INTEGER) AS half, CAST(SUM(products) AS BIGINT) AS total FROM ({_MADE_SQL}) m GROUP BY ROLLUP (engine, pos % 2)")
def metrics_rollup(spark: SparkSession, sf: str) -> DataFrame:
    return _made(spark, sf).withColumn("half", F.col("pos") % 2).rollup("engine", "half").agg(F.sum("products").alias("total"))


@register("metrics_cube", f"SELECT engine, CAST(pos % 2 AS INTEGER) AS half, CAST(SUM(products) AS BIGINT) AS total FROM ({_MADE_SQL}) m GROUP BY CUBE (engine, pos % 2)")
def metrics_cube(spark: SparkSession, sf: str) -> DataFrame:
    return _made(spark, sf).withColumn("half", F.col("pos") % 2).cube("engine", "half").agg(F.sum("products").alias("total"))


@register("metrics_moving", f"SELECT *, AVG(products) OVER (PARTITION BY engine ORDER BY pos ROWS BETWEEN 4 PRECEDING AND CURRENT ROW) AS recent FROM ({_MADE_SQL}) m")
def metrics_moving(spark: SparkSession, sf: str) -> DataFrame:
    return W.moving_average(_made(spark, sf), "products")


@register("metrics_tiles", f"SELECT engine, tile, CAST(SUM(products) AS BIGINT) AS total FROM (SELECT *, CAST(NTILE(4) OVER (PARTITION BY engine ORDER BY products, pos) AS INTEGER) AS tile FROM ({_MADE_SQL}) m) t GROUP BY 1, 2")
def metrics_tiles(spark: SparkSession, sf: str) -> DataFrame:
    return W.slowest_share(_made(spark, sf), "products")


@register("hit_rates", f"SELECT engine, CAST(SUM(cached_spans) AS DOUBLE) / COUNT(*) AS whole_rate FROM ({_MADE_SQL}) m GROUP BY 1")
def hit_rates(spark: SparkSession, sf: str) -> DataFrame:
    """The share of queries answered from a stored whole result."""
    return _made(spark, sf).groupBy("engine").agg((F.sum("cached_spans").cast("double") / F.count("*")).alias("whole_rate"))


# the overlap index over generated logs ------------------------------------------------------------


@register("overlap_linear")
def overlap_linear(spark: SparkSession, sf: str) -> DataFrame:
    """sub_path, f, entries: the index of a generated workload's queries, built at once."""
    net = commerce(spark, sf)
    index = built([parse_path(p, net, {a: c}) for _, p, a, c in W.generate_workload(net, 500, seed=1)])
    return rows_df(spark, sorted(("-".join(s), x.f, len(x.keys)) for s, x in index.internal()), "sub_path string, f long, entries long")


# generated workloads ------------------------------------------------------------------------------


def _generated(dist: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        return W.workload_df(spark, W.generate_workload(commerce(spark, sf), X.QUERIES, dist=dist, alpha=1.6)).select("pos", "session", "path", F.to_json("constraints").alias("constraints"))

    return run


register("workload_sessions")(_generated("uniform"))
register("workload_zipf")(_generated("zipf"))

_LOG_ROWS, _PARTS = 2000, 20


def _digest_share(name: str, row: str) -> str:
    return f"(CAST(('0x' || substr(md5('7|{name}|' || CAST({row} AS VARCHAR)), 1, 12)) AS BIGINT) / 281474976710656.0)"


_UNIVERSE_SQL = " UNION ALL ".join(
    "SELECT {w} AS width, {text} AS path FROM {joins} WHERE {on}".format(
        w=w,
        text=" || '-' || ".join(["t0.a", *(f"t{i}.b" for i in range(w - 1))]),
        joins=", ".join(f"steps t{i}" for i in range(w - 1)),
        on=" AND ".join(f"t{i}.b = t{i + 1}.a" for i in range(w - 2)),
    )
    for w in (3, 4, 5)
)
_ACTIVITY_STEPS = " UNION ALL ".join(f"SELECT '{a}' AS a, '{b}' AS b" for s in ("UE", "ET", "EK", "ED") for a, b in (s, s[::-1]))


@register(
    "workload_hashed",
    f"""WITH steps AS ({_ACTIVITY_STEPS}), paths AS (SELECT ROW_NUMBER() OVER (ORDER BY width, path) - 1 AS number, path, path[1] AS kind FROM ({_UNIVERSE_SQL}) u),
kinds AS (SELECT DISTINCT a AS kind FROM steps), fitting AS (SELECT kinds.kind, path, (STRPOS(path, kinds.kind) - 1) // 2 AS place, ROW_NUMBER() OVER (PARTITION BY kinds.kind ORDER BY number) - 1 AS choice FROM kinds JOIN paths ON CONTAINS(path, kinds.kind)),
sizes AS (SELECT 'E' AS kind, COUNT(DISTINCT event_id) AS nodes FROM events UNION ALL SELECT 'U', COUNT(DISTINCT user_id) FROM events UNION ALL SELECT 'T', COUNT(DISTINCT event_type) FROM events UNION ALL SELECT 'K', COUNT(DISTINCT json_extract(props, '$.k')) FROM events UNION ALL SELECT 'D', COUNT(DISTINCT DATE_TRUNC('day', ts)) FROM events),
g AS (SELECT range AS id, range * {_PARTS} // {_LOG_ROWS} AS part FROM range({_LOG_ROWS})),
f AS (SELECT *, ROW_NUMBER() OVER (PARTITION BY part ORDER BY id) = 1 OR {_digest_share('restart', 'id')} < 0.08 AS fresh FROM g),
s AS (SELECT *, MAX(CASE WHEN fresh THEN id END) OVER (PARTITION BY part ORDER BY id ROWS UNBOUNDED PRECEDING) AS start FROM f),
d AS (SELECT s.*, kind FROM s JOIN paths ON number = LEAST(CAST(FLOOR({_digest_share('kind', 'start')} * (SELECT COUNT(*) FROM paths)) AS BIGINT), (SELECT COUNT(*) FROM paths) - 1)),
c AS (SELECT d.*, LEAST(CAST(FLOOR({_digest_share('entity', 'start')} * nodes) AS BIGINT), nodes - 1) AS entity, LEAST(CAST(FLOOR({_digest_share('path', 'id')} * n) AS BIGINT), n - 1) AS choice FROM d JOIN sizes USING (kind) JOIN (SELECT kind, COUNT(*) AS n FROM fitting GROUP BY 1) k USING (kind))
SELECT md5('7|order|' || CAST(id AS VARCHAR)) AS pos, CAST(start AS BIGINT) AS session, path, CAST(place AS INTEGER) AS place, CAST(entity AS BIGINT) AS entity FROM c JOIN fitting USING (kind, choice)""",
)
def workload_hashed(spark: SparkSession, sf: str) -> DataFrame:
    """A workload from hashes alone, as for logs of any length."""
    return W.hashed_workload(activity(spark, sf), _LOG_ROWS, seed=7, parts=_PARTS)


# experiments --------------------------------------------------------------------------------------


def _sweep(name: str, engines: tuple[str, ...]) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        """Means over ten workloads of 500 queries on both networks, by engine and value of one parameter."""
        return X.compared(X.run_all(spark, sf, X.SWEEPS[name], engines, X.WORKLOADS, X.QUERIES))

    return run


for _name in ("cache_size", "data_size", "restart", "zipf"):
    register(f"sweep_{_name}")(_sweep(_name, X.CACHING))
    register(f"sweep_policy_{_name}")(_sweep(_name, X.REPLACING))

_ALL = tuple(CACHES)


def _default(spark: SparkSession, sf: str) -> DataFrame:
    return X.run_all(spark, sf, X.SWEEPS["default"], _ALL, X.WORKLOADS, X.QUERIES)


@register("experiment_answers", " UNION ALL ".join(f"SELECT '{n}' AS network, CAST({X.QUERIES * X.WORKLOADS} AS BIGINT) AS queries, CAST(0 AS BIGINT) AS differing" for n in X.CORES))
def experiment_answers(spark: SparkSession, sf: str) -> DataFrame:
    """Queries of the generated workloads to which the engines do not all give the same answer."""
    return X.answers_agree(_default(spark, sf)).select("network", "queries", "differing")


@register("experiment_cumulative")
def experiment_cumulative(spark: SparkSession, sf: str) -> DataFrame:
    """Seconds and scalar products up to each position, means over the workloads."""
    found = X.by_position(_default(spark, sf)).withColumn("engine", F.concat_ws("/", "network", "engine"))
    return W.cumulative(W.cumulative(found, "seconds").withColumnRenamed("running", "seconds_so_far"), "operations").withColumnRenamed("running", "operations_so_far")


@register("experiment_quartiles")
def experiment_quartiles(spark: SparkSession, sf: str) -> DataFrame:
    """Quartiles of seconds by position, means over the workloads."""
    return W.quartiles(X.by_position(_default(spark, sf)).withColumn("engine", F.concat_ws("/", "network", "engine")), "seconds")


@register("experiment_improvement")
def experiment_improvement(spark: SparkSession, sf: str) -> DataFrame:
    """Share of seconds and of scalar products saved against sparse plans without a cache, and the oversize rate."""
    c = X.compared(_default(spark, sf))
    base = c.filter("engine = 'sparse'").select("network", F.col("seconds").alias("s0"), F.col("mean_operations").alias("o0"))
    return c.join(base, "network").select(
        "network", "engine", (1 - F.col("seconds") / F.col("s0")).alias("seconds_saved"), (1 - F.col("mean_operations") / F.col("o0")).alias("operations_saved"),
        (F.col("rejected") / F.col("queries")).alias("oversize_rate"), (F.col("whole_hits") / F.col("queries")).alias("whole_hit_rate"), "most_bytes",
    )


@register("plan_agreement")
def plan_agreement(spark: SparkSession, sf: str) -> DataFrame:
    """network, queries, agreeing, and seconds of planning and of multiplying, under uniform and count-sketch densities, over 2,000 queries each."""
    return X.ablation(spark, sf, X.ABLATION).groupBy("network").agg(
        F.count("*").alias("queries"), F.count_if("same").alias("agreeing"), *(F.sum(c).alias(c) for c in ("uniform_planning", "sketch_planning", "uniform_multiplying", "sketch_multiplying"))
    )


@register("estimate_spread")
def estimate_spread(spark: SparkSession, sf: str) -> DataFrame:
    """Median ratio of estimated to real entries of results, by network and estimator, over 2,000 queries each."""
    a = X.ablation(spark, sf, X.ABLATION).filter("nnz > 0")
    return a.groupBy("network").agg(*(F.percentile(F.col(f"{k}_nnz") / F.col("nnz"), 0.5).alias(f"{k}_ratio") for k in ("uniform", "sketch")))


@register("cost_fit")
def cost_fit(spark: SparkSession, sf: str) -> DataFrame:
    """network, alpha, beta, gamma: the cost's weights, in nanoseconds, by least squares over products that were executed and timed, and the share of variance they explain."""
    samples = X.product_samples(spark, sf)
    rows = []
    for network in sorted(samples):
        found = [(a, b, g, 1e9 * s) for a, b, g, s in samples[network]]
        c = fit_coefficients(found, non_negative=True)
        seconds = [s for *_, s in found]
        mean = sum(seconds) / len(seconds)
        left = sum((s - c.alpha * a - c.beta * b - c.gamma * g) ** 2 for a, b, g, s in found)
        rows.append((network, len(found), c.alpha, c.beta, c.gamma, 1 - left / max(sum((s - mean) ** 2 for s in seconds), 1e-30)))
    return rows_df(spark, rows, "network string, products int, alpha double, beta double, gamma double, explained double")


@register("single_query_methods")
def single_query_methods(spark: SparkSession, sf: str) -> DataFrame:
    """method, queries, seconds: mean time a query over tables of the dense plan, the declarative traversal, sparse plans and the reference engine, on one small network."""
    net = commerce(spark, sf, keep=True)
    queries = [parse_path(p, net) for p in ("B-P-S", "S-P-B", "N-S-P", "B-P-S-N", "Y-P-S-N")]
    walker, reference = TraversalEngine(net), engine(net, "reference")
    methods: dict[str, Callable] = {
        "dense": lambda q, i: evaluate_dense(net, q, 8_000_000),
        "traversal": lambda q, i: walker.run_one(q),
        "sparse": lambda q, i: evaluate(net, q, ChainPlanner()),
        "reference": lambda q, i: reference.run_one(q, i),
    }
    rows, answers = [], {}
    for name, answer in methods.items():
        summary(answer(queries[0], 0)).first()  # compiles code and keeps matrices
        t = time.perf_counter()
        answers[name] = [tuple(summary(answer(q, i)).first()) for i, q in enumerate(queries)]
        rows.append((name, len(queries), (time.perf_counter() - t) / len(queries), answers[name] == answers["dense"]))
    walker.close()
    return rows_df(spark, rows, "method string, queries int, seconds double, same_answers boolean")


# network statistics -------------------------------------------------------------------------------

_CORE_EDGES = (("C-O", "CO", 1), ("O-P", "OP", 0), ("O-S", "OS", 0), ("O-M", "OM", 0))


def _split_sql(percent: int) -> str:
    """Nodes and edges of a split by type."""
    core = f"SELECT o_orderkey AS id FROM orders WHERE o_orderkey % 100 < {percent}"
    step = {n: f"SELECT DISTINCT s, d FROM ({STEP_SQL[k]}) a WHERE {'d' if end else 's'} IN ({core})" for n, k, end in _CORE_EDGES}
    ids = {"O": core, "C": f"SELECT DISTINCT s AS id FROM ({step['C-O']}) x", **{t: f"SELECT DISTINCT d AS id FROM ({step[f'O-{t}']}) x" for t in "PSM"}}
    nodes = [("node", t, f"SELECT id FROM ({q}) y") for t, q in ids.items()]
    nodes += [("node", t, f"SELECT DISTINCT {c} FROM {table}") for t, c, table in (("N", "n_nationkey", "nation"), ("R", "r_regionkey", "region"), ("B", "p_brand", "part"), ("Y", "p_type", "part"), ("G", "c_mktsegment", "customer"))]
    beside = {"P-S": ("PS", "P", "S"), "C-N": ("CN", "C", None), "S-N": ("SN", "S", None), "N-R": ("NR", None, None), "P-B": ("PB", "P", None), "P-Y": ("PY", "P", None), "C-G": ("CG", "C", None)}
    for n, (k, a, b) in beside.items():
        on = [f"{c} IN ({ids[t]})" for c, t in (("s", a), ("d", b)) if t]
        step[n] = f"SELECT DISTINCT s, d FROM ({STEP_SQL[k]}) a" + (f" WHERE {' AND '.join(on)}" if on else "")
    step["next"] = f"SELECT s, d FROM ({STEP_SQL['next']}) a WHERE s IN ({core}) AND d IN ({core})"
    parts = nodes + [("edge", n, q) for n, q in step.items()]
    return " UNION ALL ".join(f"SELECT CAST({percent} AS INTEGER) AS percent, '{kind}' AS kind, '{n}' AS name, CAST(COUNT(*) AS BIGINT) AS n FROM ({q}) z" for kind, n, q in parts)


@register("net_split_types", " UNION ALL ".join(f"({_split_sql(p)})" for p in X.SPLITS))
def net_split_types(spark: SparkSession, sf: str) -> DataFrame:
    """Nodes and edges by type of the network's splits."""
    net = commerce(spark, sf)
    return X.union([net.core_split("O", p).stats().select(F.lit(p).alias("percent"), "kind", "name", "n") for p in X.SPLITS])


@register("net_splits", f"SELECT percent, CAST(SUM(CASE WHEN kind = 'node' THEN n END) AS BIGINT) AS nodes, CAST(SUM(CASE WHEN kind = 'edge' THEN n END) AS BIGINT) AS edges, 2.0 * SUM(CASE WHEN kind = 'edge' THEN n END) / SUM(CASE WHEN kind = 'node' THEN n END) AS degree FROM ({' UNION ALL '.join(f'({_split_sql(p)})' for p in X.SPLITS)}) t GROUP BY 1")
def net_splits(spark: SparkSession, sf: str) -> DataFrame:
    """Nodes, edges and average degree of the network's splits."""
    of = lambda k: F.sum(F.when(F.col("kind") == k, F.col("n")))
    return net_split_types(spark, sf).groupBy("percent").agg(of("node").alias("nodes"), of("edge").alias("edges"), (2.0 * of("edge") / of("node")).alias("degree"))


@register("net_split_kept", "SELECT CAST(COUNT(*) AS BIGINT) AS orders FROM orders WHERE o_orderkey % 100 < 60 OR o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')")
def net_split_kept(spark: SparkSession, sf: str) -> DataFrame:
    """Core nodes of a split that keeps all those linked with one segment, as the news network's splits keep articles on companies."""
    net = commerce(spark, sf)
    linked = evaluate(net, parse_path("C-O", net, {0: "c_mktsegment='BUILDING'"})).select(F.col("dst").alias("id"))
    return net.core_split("O", 60, always_keep=linked).nodes["O"].df.agg(F.count("*").alias("orders"))
