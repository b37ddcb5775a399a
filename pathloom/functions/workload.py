"""Workloads: generated sessions, their overlaps, and measures over runs."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from pathloom.plans.query import PathQuery, parse_path
from pathloom.sources.networks import TypedNetwork
from pathloom.sources.storage import WORKLOAD_SCHEMA

#: Thirty queries of six sessions over the commerce network, (session, path, position, predicate) by place.
FIXED_30 = (
    (1, "C-O-P", 0, "C=7"), (3, "P-S-N", 0, "P=42"), (6, "B-P-S-N", 0, "p_brand='Brand#7'"), (2, "C-O-P-S", 0, "C=11"), (5, "N-C-O-P", 2, "o_orderdate>=DATE'2001-01-01'"),
    (2, "C-O-P", 0, "C=11"), (4, "S-P-Y", 0, "S=3"), (1, "C-O-P-B", 0, "C=7"), (3, "P-S-N-R", 0, "P=42"), (6, "B-P-O", 0, "p_brand='Brand#7'"),
    (3, "P-O-C", 0, "P=42"), (5, "G-C-O-P-B", 2, "o_orderdate>=DATE'2001-01-01'"), (2, "C-O-P-B", 0, "C=11"), (4, "S-O-P-B", 0, "S=3"), (1, "C-O-P-Y", 0, "C=7"),
    (4, "S-O-C", 0, "S=3"), (6, "B-P-O-C", 0, "p_brand='Brand#7'"), (3, "P-O-C-N", 0, "P=42"), (5, "C-O-P-O-C", 1, "o_orderdate>=DATE'2001-01-01'"), (2, "C-O-S-N", 0, "C=11"),
    (5, "C-O-P", 1, "o_orderdate>=DATE'2001-01-01'"), (1, "C-O-S", 0, "C=7"), (4, "S-O-C-G", 0, "S=3"), (6, "B-P-O-C-G", 0, "p_brand='Brand#7'"), (3, "P-O-C-G", 0, "P=42"),
    (6, "B-P-S", 0, "p_brand='Brand#7'"), (2, "C-O-M", 0, "C=11"), (5, "C-O-P-B", 1, "o_orderdate>=DATE'2001-01-01'"), (1, "C-O-P-O-C", 0, "C=7"), (4, "S-P-B", 0, "S=3"),
)


def fixed_30(net: TypedNetwork | None = None) -> list[PathQuery]:
    return [parse_path(path, net, {at: predicate}) for _, path, at, predicate in FIXED_30]


def workload_df(spark: SparkSession, rows) -> DataFrame:
    """(pos, session, path, constraints) of rows (session, path, position, predicate)."""
    return spark.createDataFrame([(i, s, p, {a: c}) for i, (s, p, a, c) in enumerate(rows)], WORKLOAD_SCHEMA)


def queries_of(workload: DataFrame, net: TypedNetwork | None = None) -> list[PathQuery]:
    """The queries of a workload in order; a workload is as small as its log."""
    return [parse_path(r["path"], net, r["constraints"]) for r in workload.orderBy("pos").collect()]


def path_universe(net, lengths: tuple[int, ...] = (3, 4, 5)) -> list[tuple[str, ...]]:
    """All walks over the type graph with these numbers of types, by length and then alphabet."""
    after: dict[str, list[str]] = {}
    for a, b in sorted(net.steps()):
        after.setdefault(a, []).append(b)
    paths = [(t,) for t in sorted(after)]
    universe: list[tuple[str, ...]] = []
    for length in range(2, max(lengths) + 1):
        paths = [(*p, t) for p in paths for t in after.get(p[-1], [])]
        if length in lengths:
            universe += paths
    return universe


def generate_workload(
    net, n: int = 500, restart_p: float = 0.08, lengths: tuple[int, ...] = (3, 4, 5), dist: str = "uniform", alpha: float = 1.2, seed: int = 0, shuffle: bool = True, entities: str = "nodes"
) -> list[tuple[int, str, int, str]]:
    """Rows (session, path, position, predicate): sessions about one entity each.

    At each step a new entity is drawn with probability restart_p, else the session goes on with another
    path that has the entity's type. Paths and entities are drawn uniformly or by Zipf's law over a seeded
    order of the paths, and of the keys that the network has. entities tells what all entities are: nodes, each
    of which is one constraint, so large types have more sessions; or types, of which one is drawn first, so
    the few nodes of small types have as many. The finished log is shuffled.
    """
    rng = np.random.Generator(np.random.PCG64(seed))
    universe = path_universe(net, lengths)
    order = rng.permutation(len(universe))
    shares: dict[int, np.ndarray] = {}

    def draw(size: int) -> int:
        if dist == "uniform":
            return int(rng.integers(size))
        if size not in shares:
            weights = np.cumsum(np.arange(1, size + 1, dtype=float) ** -alpha)
            shares[size] = weights / weights[-1]
        return min(int(np.searchsorted(shares[size], rng.random(), "right")), size - 1)

    sizes = {t: net.size(t) for t in sorted({t for p in universe for t in p})}

    def entity(place: int) -> tuple[str, int]:
        """The node at a place of the seeded order of all nodes: scattered by a hash, so no order has to be made."""
        at = int(np.random.Generator(np.random.PCG64([seed, place])).integers(sum(sizes.values())))
        for t, size in sizes.items():
            if at < size:
                return t, at
            at -= size
        raise IndexError(place)

    steps: list[tuple[int, str, int, int]] = []  # session, path, position, rank of the entity
    kinds: list[str] = []
    fitting: dict[str, list] = {}
    session, kind, rank = 0, "", 0
    for i in range(n):
        if i == 0 or rng.random() < restart_p:
            session += 1
            if entities == "types":
                kind = universe[order[draw(len(universe))]][0]
                rank = draw(max(1, net.size(kind)))
            else:
                kind, rank = entity(draw(sum(sizes.values())))
        if kind not in fitting:
            fitting[kind] = [universe[p] for p in order if kind in universe[p]]
        path = fitting[kind][draw(len(fitting[kind]))]
        steps.append((session, "-".join(path), path.index(kind), rank))
        kinds.append(kind)
    keys = {k: net.keys_at(k, sorted({s[3] for s, t in zip(steps, kinds, strict=True) if t == k}), seed) for k in sorted(set(kinds))}
    rows = [(s, path, at, f"id = {keys[k][rank]}") for (s, path, at, rank), k in zip(steps, kinds, strict=True)]
    return [rows[i] for i in rng.permutation(n)] if shuffle else rows


def _share(*parts: Column | str | int) -> Column:
    """A number in [0, 1) from the digest of its parts."""
    text = F.concat_ws("|", *(p if isinstance(p, Column) else F.lit(str(p)) for p in parts))
    return F.conv(F.substring(F.md5(text), 1, 12), 16, 10).cast("long") / F.lit(float(1 << 48))


def hashed_workload(net: TypedNetwork, n: int, restart_p: float = 0.08, lengths: tuple[int, ...] = (3, 4, 5), alpha: float | None = None, seed: int = 0, parts: int = 200) -> DataFrame:
    """(pos, session, path, place, entity): as generate_workload, for logs of any length, from hashes alone.

    Every draw is a digest of the seed, its name and a row number, so a log is the same under any
    partitioning. Sessions are numbered within ``parts`` stretches of the log (each starts one), so no task sees
    all of it. entity is the rank of the session's node in its type; with alpha ranks and paths follow Zipf's law,
    by the continuous inverse of its distribution.
    """
    spark = net.spark
    universe = path_universe(net, lengths)
    paths = spark.createDataFrame([(i, "-".join(p), p[0]) for i, p in enumerate(universe)], "number int, first_path string, kind string")
    fits: dict[str, list] = {}
    for p in universe:
        for t in sorted(set(p)):
            fits.setdefault(t, []).append(("-".join(p), p.index(t)))
    fitting = spark.createDataFrame([(t, i, *x) for t, found in sorted(fits.items()) for i, x in enumerate(found)], "kind string, choice int, path string, place int")
    sizes = spark.createDataFrame([(t, len(found), net.size(t)) for t, found in sorted(fits.items())], "kind string, choices int, nodes long")

    def pick(u: Column, size: Column) -> Column:
        if alpha is None:
            at = F.floor(u * size)
        elif alpha == 1:
            at = F.floor(F.pow(size + 1.0, u)) - 1
        else:
            at = F.floor(F.pow(u * (F.pow(size + 1.0, F.lit(1 - alpha)) - 1) + 1, F.lit(1 / (1 - alpha)))) - 1
        return F.least(at.cast("long"), size.cast("long") - 1)

    steps = spark.range(n).select(F.col("id"), F.floor(F.col("id") * parts / n).cast("int").alias("part"))
    running = Window.partitionBy("part").orderBy("id")
    fresh = (F.row_number().over(running) == 1) | (_share(seed, "restart", F.col("id").cast("string")) < restart_p)
    steps = steps.withColumn("start", F.max(F.when(fresh, F.col("id"))).over(running.rowsBetween(Window.unboundedPreceding, 0)))
    start, step = F.col("start").cast("string"), F.col("id").cast("string")
    drawn = steps.withColumn("number", pick(_share(seed, "kind", start), F.lit(len(universe))).cast("int")).join(F.broadcast(paths), "number").join(F.broadcast(sizes), "kind")
    drawn = drawn.withColumn("entity", pick(_share(seed, "entity", start), F.col("nodes"))).withColumn("choice", pick(_share(seed, "path", step), F.col("choices")).cast("int"))
    full = drawn.join(F.broadcast(fitting), ["kind", "choice"])
    return full.select(F.md5(F.concat_ws("|", F.lit(str(seed)), F.lit("order"), step)).alias("pos"), F.col("start").alias("session"), "path", "place", "entity")


def subpaths(path: Column) -> Column:
    """All contiguous sub-paths of two types or more of dashed text, as an array."""
    parts = F.split(path, "-")
    n = F.size(parts)
    spans = F.transform(F.sequence(F.lit(1), n - 1), lambda i: F.transform(F.sequence(F.lit(2), n - i + 1), lambda w: F.array_join(F.slice(parts, i, w), "-")))
    return F.flatten(spans)


def mine_overlaps(workload: DataFrame, min_freq: int = 2) -> DataFrame:
    """sub_path, f: contiguous sub-paths that occur at least min_freq times, over logs of any size."""
    return workload.select(F.explode(subpaths(F.col("path"))).alias("sub_path")).groupBy("sub_path").agg(F.count("*").alias("f")).filter(F.col("f") >= min_freq)


def mine_constrained_overlaps(workload: DataFrame, min_freq: int = 2) -> DataFrame:
    """sub_path, ckey, f, maximal: as mine_overlaps, by constraints (a map from positions to predicates).

    ckey has the sub-path's own constraints, counted from its start. maximal tells the sub-paths that the
    overlap index has a node for: seen with different next types, or at a query's end.
    """
    parts = F.split("path", "-")
    n = F.size("parts")
    spans = F.flatten(F.transform(F.sequence(F.lit(0), n - 2), lambda i: F.transform(F.sequence(i + 1, n - 1), lambda j: F.struct(i.alias("i"), j.alias("j")))))
    rows = workload.withColumn("parts", parts).select("parts", "constraints", F.explode(spans).alias("s"))
    inside = F.map_filter(F.coalesce("constraints", F.create_map().cast("map<int,string>")), lambda p, c: (p >= F.col("s.i")) & (p <= F.col("s.j")))
    moved = F.array_sort(F.map_entries(F.transform_keys(inside, lambda p, c: p - F.col("s.i"))))
    text = F.array_join(F.transform(moved, lambda e: F.concat_ws(":", e["key"].cast("string"), e["value"])), " & ")
    found = rows.select(
        F.array_join(F.slice("parts", F.col("s.i") + 1, F.col("s.j") - F.col("s.i") + 1), "-").alias("sub_path"), text.alias("ckey"), F.get("parts", F.col("s.j") + 1).alias("next")
    )
    by_key = found.groupBy("sub_path", "ckey").agg(F.count("*").alias("f"))
    shape = found.groupBy("sub_path").agg((F.count_distinct("next") + F.count_if(F.col("next").isNull()) > 1).alias("maximal"))
    return by_key.join(shape, "sub_path").filter(F.col("f") >= min_freq).select("sub_path", "ckey", "f", "maximal")


@udtf(returnType="sub_path string, start int, length int")
class SubPaths:
    """For SQL: the contiguous sub-paths of two types or more of a dashed path."""

    def eval(self, path: str):
        parts = path.split("-") if path else []
        for i in range(len(parts)):
            for j in range(i + 2, len(parts) + 1):
                yield "-".join(parts[i:j]), i, j - i


def cumulative(metrics: DataFrame, value: str = "exec_seconds") -> DataFrame:
    """metrics with running, the sum of a measure up to each query of an engine."""
    w = Window.partitionBy("engine").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    return metrics.withColumn("running", F.sum(value).over(w))


def quartiles(metrics: DataFrame, value: str = "exec_seconds") -> DataFrame:
    """engine, q1, q2, q3 of a measure."""
    return metrics.groupBy("engine").agg(*(F.percentile(value, p).alias(f"q{i}") for i, p in enumerate((0.25, 0.5, 0.75), 1)))


def improvement(metrics: DataFrame, baseline: str, value: str = "exec_seconds") -> DataFrame:
    """engine, mean, improvement over a baseline: 1 - mean / its mean."""
    means = metrics.groupBy("engine").agg(F.avg(value).alias("mean"))
    base = means.filter(F.col("engine") == baseline).select(F.col("mean").alias("base"))
    return means.join(F.broadcast(base)).select("engine", "mean", (1 - F.col("mean") / F.col("base")).alias("improvement"))


def moving_average(metrics: DataFrame, value: str = "exec_seconds", before: int = 4) -> DataFrame:
    """metrics with recent, the mean of a measure over a query and those just before it."""
    w = Window.partitionBy("engine").orderBy("pos").rowsBetween(-before, 0)
    return metrics.withColumn("recent", F.avg(value).over(w))


def slowest_share(metrics: DataFrame, value: str = "exec_seconds", tiles: int = 4) -> DataFrame:
    """engine, tile, total: a measure's sum over each tile of the queries, from the least to the most."""
    w = Window.partitionBy("engine").orderBy(value, "pos")
    return metrics.withColumn("tile", F.ntile(tiles).over(w)).groupBy("engine", "tile").agg(F.sum(value).alias("total"))
