"""Typed networks over tables: node types with properties, edge types as pairs of keys."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathloom.plans.cost import MatrixStats
from pathloom.plans.query import normalised

from .storage import read_table, stored, stored_counted


#: Largest domain that is numbered by one task.
SMALL_DOMAIN = 1_000_000
#: Hash ranges in which nodes are ranked.
RANK_BUCKETS = 1024


@dataclass(frozen=True)
class NodeType:
    """Nodes: a DataFrame with the column id (long) and properties. key is the property that id repeats, label the one that names a node."""

    name: str
    df: DataFrame
    label: str = "id"
    key: str = "id"


@dataclass(frozen=True)
class EdgeType:
    """Edges: a DataFrame (src, dst), parallel edges as repeated rows. Bidirectional ones can be walked backward."""

    name: str
    src: str
    dst: str
    df: DataFrame
    bidirectional: bool = True


@dataclass
class TypedNetwork:
    name: str
    spark: SparkSession
    nodes: dict[str, NodeType]
    edges: list[EdgeType]
    weight: str = "binary"
    #: Keep each step's matrix, once it is used, as a table sorted by src; else matrices are read off the source tables each time.
    keep: bool = False
    counted: dict = field(default_factory=dict)
    kept: dict = field(default_factory=dict)

    def edge(self, src: str, dst: str, name: str | None = None) -> tuple[EdgeType, bool]:
        """The edge type for a step and whether it is walked backward. Without a name it must be the only unnamed one."""
        for e in self.edges:
            if (e.name == name if name else not e.name.startswith("next")):
                if (e.src, e.dst) == (src, dst):
                    return e, False
                if e.bidirectional and (e.dst, e.src) == (src, dst):
                    return e, True
        raise KeyError(f"no edge type {name or ''} from {src} to {dst}")

    def adjacency(self, src: str, dst: str, name: str | None = None, weight: str | None = None) -> DataFrame:
        """The step's matrix as (src, dst, n) with unique pairs; n is 1, or the number of parallel edges."""
        e, back = self.edge(src, dst, name)
        weight = weight or self.weight
        key = (e.name, back, weight)
        if key not in self.kept and (e.name, not back, weight) in self.kept:
            x = self.kept[e.name, not back, weight]  # its pairs are unique already, so the other direction takes no exchange
            turned = x.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "n")
            self.kept[key] = stored(turned.sortWithinPartitions("src", "dst"), "adjacency")
        elif key not in self.kept:
            pairs = e.df.select(F.col("dst").alias("src"), F.col("src").alias("dst")) if back else e.df.select("src", "dst")
            if weight == "multiplicity":
                matrix = pairs.groupBy("src", "dst").agg(F.count("*").alias("n"))
            else:
                matrix = pairs.distinct().withColumn("n", F.lit(1).cast("long"))
            if not self.keep:
                return matrix
            self.kept[key], self.counted["edges", e.name, weight] = stored_counted(matrix.sortWithinPartitions("src", "dst"), "adjacency")
        return self.kept[key]

    def selection(self, node_type: str, predicate: str) -> DataFrame:
        """The keys (id) of a type's nodes for which a predicate holds; type = value stands for its key."""
        return self.nodes[node_type].df.filter(F.expr(self.expanded(node_type, predicate))).select("id")

    def expanded(self, node_type: str, predicate: str) -> str:
        return normalised(predicate, node_type, self.key_names(node_type))

    def key_names(self, node_type: str) -> tuple[str, ...]:
        """What predicates may call a type's key besides id and the type's letter."""
        return (self.nodes[node_type].key,)

    def size(self, node_type: str) -> int:
        if node_type not in self.counted:
            self.counted[node_type] = self.nodes[node_type].df.count()
        return self.counted[node_type]

    def step_stats(self, src: str, dst: str, name: str | None = None, exact: bool = False) -> MatrixStats:
        """Rows, columns and entries of a step's matrix, once per edge type.

        Entries of kept matrices are counted while those are written. Of others the rows of the edge table are
        counted instead, which needs no exchange and counts parallel edges too; exact counts distinct pairs.
        """
        e, back = self.edge(src, dst, name)
        key = ("edges", e.name, self.weight)
        if key not in self.counted and self.keep:
            self.adjacency(src, dst, name)
        elif key not in self.counted and exact:
            self.counted[key] = self.adjacency(src, dst, name).count()
        if key in self.counted:
            return MatrixStats(self.size(src), self.size(dst), self.counted[key])
        if ("rows", e.name) not in self.counted:
            self.counted["rows", e.name] = e.df.count()
        rows, cols = self.size(src), self.size(dst)
        return MatrixStats(rows, cols, min(self.counted["rows", e.name], rows * cols))

    def share(self, node_type: str, predicate: str) -> float:
        """The share of a type's nodes for which a predicate holds."""
        key = ("share", node_type, predicate)
        if key not in self.counted:
            text = self.expanded(node_type, predicate)
            found = 1 if text.startswith("id = ") else self.selection(node_type, predicate).count()
            self.counted[key] = found / max(1, self.size(node_type))
        return self.counted[key]

    def infer_schema(self) -> DataFrame:
        """src_type, edge_type, dst_type, n_edges: the type graph that the data imply."""
        parts = [e.df.distinct().groupBy().agg(F.count("*").alias("n_edges")).select(F.lit(e.src).alias("src_type"), F.lit(e.name).alias("edge_type"), F.lit(e.dst).alias("dst_type"), "n_edges") for e in self.edges]
        return reduce(DataFrame.unionByName, parts)

    def steps(self) -> list[tuple[str, str]]:
        """All steps of one letter type to another, backward ones too, without named relations."""
        return sorted({s for e in self.edges if not e.name.startswith("next") for s in ([(e.src, e.dst)] + [(e.dst, e.src)] * e.bidirectional)})

    def type_edges(self) -> DataFrame:
        return self.spark.createDataFrame(self.steps(), "src_type string, dst_type string")

    def keys_at(self, node_type: str, ranks: list[int], seed: int = 0) -> dict[int, int]:
        """The keys at the given ranks (from 0) in a seeded order of a type's nodes.

        Nodes are counted by ranges of a hash first; then only the ranges that hold a rank are put in order, one
        apart from the other, so no task sees all nodes and only the asked-for keys reach the driver.
        """
        h = F.xxhash64(F.col("id"), F.lit(seed))
        nodes = self.nodes[node_type].df.select("id", h.alias("h")).withColumn("bucket", F.pmod("h", F.lit(RANK_BUCKETS)).cast("int"))
        counts = sorted((r["bucket"], r["count"]) for r in nodes.groupBy("bucket").count().collect())  # one row for each range
        wanted, start = [], 0
        left = sorted(set(ranks))
        for bucket, n in counts:
            while left and left[0] < start + n:
                wanted.append((bucket, left[0] - start + 1, left.pop(0)))
            start += n
        if left:
            raise IndexError(f"{node_type} has {start} nodes")
        order = Window.partitionBy("bucket").orderBy("h", "id")
        places = self.spark.createDataFrame(wanted, "bucket int, place int, rank long")
        few = nodes.join(F.broadcast(places.select("bucket").distinct()), "bucket", "left_semi").withColumn("place", F.row_number().over(order))
        return {r["rank"]: r["id"] for r in few.join(F.broadcast(places), ["bucket", "place"]).select("rank", "id").collect()}

    def schema_paths(self, length: int) -> DataFrame:
        """All walks of a number of types over the type graph, as dashed text."""
        steps = self.type_edges()
        paths = steps.select(F.concat_ws("-", "src_type", "dst_type").alias("path"), F.col("dst_type").alias("last"))
        for _ in range(length - 2):
            paths = paths.join(steps, F.col("last") == F.col("src_type")).select(F.concat_ws("-", "path", "dst_type").alias("path"), F.col("dst_type").alias("last"))
        return paths.select("path")

    def stats(self) -> DataFrame:
        """kind, name, n of node and edge types."""
        parts = [n.df.groupBy().agg(F.count("*").alias("n")).select(F.lit("node").alias("kind"), F.lit(k).alias("name"), "n") for k, n in self.nodes.items()]
        parts += [e.df.distinct().groupBy().agg(F.count("*").alias("n")).select(F.lit("edge").alias("kind"), F.lit(e.name).alias("name"), "n") for e in self.edges]
        return reduce(DataFrame.unionByName, parts)

    def average_degree(self) -> float:
        rows = self.stats().groupBy("kind").agg(F.sum("n").alias("n")).collect()
        n = {r["kind"]: r["n"] for r in rows}
        return 2 * n["edge"] / n["node"]

    def core_split(self, core: str, percent: int, always_keep: DataFrame | None = None) -> TypedNetwork:
        """The network around a share of its core nodes: id % 100 below percent, or in always_keep; other nodes stay while still connected."""
        kept = self.nodes[core].df.filter(F.col("id") % 100 < percent).select("id")
        if always_keep is not None:
            kept = kept.union(always_keep.select("id")).distinct()
        edges = []
        for e in self.edges:
            df = e.df
            if e.src == core:
                df = df.join(kept.withColumnRenamed("id", "src"), "src", "left_semi")
            if e.dst == core:
                df = df.join(kept.withColumnRenamed("id", "dst"), "dst", "left_semi")
            edges.append(EdgeType(e.name, e.src, e.dst, df.select("src", "dst"), e.bidirectional))
        nodes, left = {}, {core: kept}
        for k, n in self.nodes.items():
            touched = [e.df.select(F.col("src").alias("id")) for e in edges if e.src == k and core in (e.src, e.dst)] + [e.df.select(F.col("dst").alias("id")) for e in edges if e.dst == k and core in (e.src, e.dst)]
            ids = kept if k == core else reduce(DataFrame.union, touched).distinct() if touched else None
            if ids is not None:
                left[k] = ids
            nodes[k] = n if ids is None else NodeType(k, n.df.join(ids, "id", "left_semi"), n.label, n.key)
        for i, e in enumerate(edges):
            if core not in (e.src, e.dst):  # edges beside the core go with nodes that are no longer connected
                df = e.df
                for side, t in (("src", e.src), ("dst", e.dst)):
                    df = df.join(left[t].withColumnRenamed("id", side), side, "left_semi") if t in left else df
                edges[i] = EdgeType(e.name, e.src, e.dst, df.select("src", "dst"), e.bidirectional)
        return TypedNetwork(f"{self.name}_{percent}", self.spark, nodes, edges, self.weight, self.keep)

    def with_appended(self, edge_name: str, more: DataFrame) -> TypedNetwork:
        """The network with edges (src, dst) appended to an edge type. Matrices kept for other types stay in use."""
        edges = [EdgeType(e.name, e.src, e.dst, e.df.select("src", "dst").unionByName(more.select("src", "dst")), e.bidirectional) if e.name == edge_name else e for e in self.edges]
        out = TypedNetwork(self.name, self.spark, self.nodes, edges, self.weight, self.keep)
        out.counted = {k: v for k, v in self.counted.items() if edge_name not in k}
        out.kept = {k: v for k, v in self.kept.items() if k[0] != edge_name}
        return out

    def register(self, prefix: str = "net") -> None:
        """Node and edge types as temporary views."""
        for k, n in self.nodes.items():
            n.df.createOrReplaceTempView(f"{prefix}_{self.name}_{k.lower()}")
        for e in self.edges:
            e.df.createOrReplaceTempView(f"{prefix}_{self.name}_{e.name.lower().replace('-', '_')}")


def dictionary(values: DataFrame, large: bool = False, most: int = SMALL_DOMAIN) -> DataFrame:
    """(id, name) of the distinct non-null values of a one-column DataFrame, numbered from 1 in order.

    A small domain is numbered by one task, which fails beyond ``most`` values; with large, ranges of values are
    numbered apart and shifted by the sizes of the ranges before.
    """
    names = values.toDF("name").filter("name is not null").distinct()
    if not large:
        number = F.row_number().over(Window.orderBy("name")).cast("long")
        checked = F.when(number > most, F.raise_error(F.lit("this domain needs large=True")).cast("long")).otherwise(number)
        return names.select(checked.alias("id"), "name")
    placed = stored(names.repartitionByRange("name").withColumn("part", F.spark_partition_id()), "names")
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # one row for each range
    starts = placed.groupBy("part").agg(F.count("*").alias("n")).select("part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    within = placed.withColumn("at", F.row_number().over(Window.partitionBy("part").orderBy("name")))
    return within.join(F.broadcast(starts), "part").select((F.col("start") + F.col("at")).alias("id"), "name")


def from_property_graph(name: str, vertices: DataFrame, edges: DataFrame) -> TypedNetwork:
    """A network from vertices (id, type, properties...) and edges (src, dst, type); types of ends are read from the data."""
    spark = vertices.sparkSession
    kinds = [r[0] for r in vertices.select("type").distinct().collect()]  # types, not nodes
    nodes = {k: NodeType(k, vertices.filter(F.col("type") == k).drop("type")) for k in sorted(kinds)}
    types = vertices.select("id", "type")
    ends = edges.join(types.select(F.col("id").alias("src"), F.col("type").alias("st")), "src").join(types.select(F.col("id").alias("dst"), F.col("type").alias("dt")), "dst")
    found = [tuple(r) for r in ends.select("type", "st", "dt").distinct().collect()]
    return TypedNetwork(name, spark, nodes, [EdgeType(t, s, d, ends.filter((F.col("type") == t) & (F.col("st") == s) & (F.col("dt") == d)).select("src", "dst")) for t, s, d in sorted(found)])


def _keyed(df: DataFrame, key: str) -> DataFrame:
    return df.withColumn("id", F.col(key).cast("long"))


def _pairs(df: DataFrame, src: str, dst: str) -> DataFrame:
    return df.filter(f"{src} is not null and {dst} is not null").select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"))


def _named(df: DataFrame, key: str, value: str, names: DataFrame) -> DataFrame:
    """Edges from keys to dictionary entries; the dictionary is small, its join may broadcast."""
    return df.select(F.col(key).cast("long").alias("src"), F.col(value).alias("name")).join(names, "name").select("src", F.col("id").alias("dst"))


def commerce(spark: SparkSession, folder: str, keep: bool = False) -> TypedNetwork:
    """Customers, orders, parts, suppliers, nations, regions, brands, part types, segments and order months."""
    t = {n: read_table(spark, folder, n) for n in ("customer", "orders", "lineitem", "part", "supplier", "nation", "region")}
    month = t["orders"].withColumn("month", F.date_trunc("month", "o_orderdate"))
    brands, kinds, segments, months = (dictionary(d.select(c)) for d, c in ((t["part"], "p_brand"), (t["part"], "p_type"), (t["customer"], "c_mktsegment"), (month, "month")))
    nodes = [
        NodeType("C", _keyed(t["customer"], "c_custkey"), "c_name", "c_custkey"),
        NodeType("O", _keyed(t["orders"], "o_orderkey"), key="o_orderkey"),
        NodeType("P", _keyed(t["part"], "p_partkey"), "p_name", "p_partkey"),
        NodeType("S", _keyed(t["supplier"], "s_suppkey"), "s_name", "s_suppkey"),
        NodeType("N", _keyed(t["nation"], "n_nationkey"), "n_name", "n_nationkey"),
        NodeType("R", _keyed(t["region"], "r_regionkey"), "r_name", "r_regionkey"),
        NodeType("B", brands.withColumn("p_brand", F.col("name")), "name"),
        NodeType("Y", kinds.withColumn("p_type", F.col("name")), "name"),
        NodeType("G", segments.withColumn("c_mktsegment", F.col("name")), "name"),
        NodeType("M", months.withColumn("month", F.col("name")), "name"),
    ]
    following = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    after = t["orders"].select(F.col("o_orderkey").alias("src"), F.lead("o_orderkey").over(following).alias("dst")).filter("dst is not null")
    edges = [
        EdgeType("C-O", "C", "O", _pairs(t["orders"], "o_custkey", "o_orderkey")),
        EdgeType("O-P", "O", "P", _pairs(t["lineitem"], "l_orderkey", "l_partkey")),
        EdgeType("O-S", "O", "S", _pairs(t["lineitem"], "l_orderkey", "l_suppkey")),
        EdgeType("P-S", "P", "S", _pairs(t["lineitem"], "l_partkey", "l_suppkey")),
        EdgeType("C-N", "C", "N", _pairs(t["customer"], "c_custkey", "c_nationkey")),
        EdgeType("S-N", "S", "N", _pairs(t["supplier"], "s_suppkey", "s_nationkey")),
        EdgeType("N-R", "N", "R", _pairs(t["nation"], "n_nationkey", "n_regionkey")),
        EdgeType("P-B", "P", "B", _named(t["part"], "p_partkey", "p_brand", brands)),
        EdgeType("P-Y", "P", "Y", _named(t["part"], "p_partkey", "p_type", kinds)),
        EdgeType("C-G", "C", "G", _named(t["customer"], "c_custkey", "c_mktsegment", segments)),
        EdgeType("O-M", "O", "M", _named(month, "o_orderkey", "month", months)),
        EdgeType("next", "O", "O", after, bidirectional=False),
    ]
    return TypedNetwork("commerce", spark, {n.name: n for n in nodes}, edges, keep=keep)


def activity(spark: SparkSession, folder: str, keep: bool = False) -> TypedNetwork:
    """A star of events with users, event types, the key in their JSON properties, and days."""
    e = read_table(spark, folder, "events")
    e = e.withColumn("k", F.get_json_object("props", "$.k").cast("long")).withColumn("day", F.date_trunc("day", "ts"))
    types, days = dictionary(e.select("event_type")), dictionary(e.select("day"))
    nodes = [
        NodeType("E", _keyed(e, "event_id"), key="event_id"),
        NodeType("U", e.select(F.col("user_id").cast("long").alias("id")).distinct()),
        NodeType("T", types.withColumn("event_type", F.col("name")), "name"),
        NodeType("K", e.filter("k is not null").select(F.col("k").alias("id")).distinct()),
        NodeType("D", days.withColumn("day", F.col("name")), "name"),
    ]
    edges = [
        EdgeType("U-E", "U", "E", _pairs(e, "user_id", "event_id")),
        EdgeType("E-T", "E", "T", _named(e, "event_id", "event_type", types)),
        EdgeType("E-K", "E", "K", _pairs(e, "event_id", "k")),
        EdgeType("E-D", "E", "D", _named(e, "event_id", "day", days)),
    ]
    return TypedNetwork("activity", spark, {n.name: n for n in nodes}, edges, keep=keep)


def corpus(spark: SparkSession, folder: str, keep: bool = False) -> TypedNetwork:
    """Documents with their languages, sources and labels."""
    d, labels = read_table(spark, folder, "documents").select("doc_id", "lang", "source", "n_chars"), read_table(spark, folder, "labels")
    langs, sources = dictionary(d.select("lang")), dictionary(d.select("source"))
    nodes = [
        NodeType("D", _keyed(d, "doc_id"), key="doc_id"),
        NodeType("L", langs.withColumn("lang", F.col("name")), "name"),
        NodeType("Z", sources.withColumn("source", F.col("name")), "name"),
        NodeType("Q", labels.select(F.col("quality").cast("long").alias("id")).distinct()),
        NodeType("X", labels.select(F.col("toxic").cast("long").alias("id")).distinct()),
    ]
    edges = [
        EdgeType("D-L", "D", "L", _named(d, "doc_id", "lang", langs)),
        EdgeType("D-Z", "D", "Z", _named(d, "doc_id", "source", sources)),
        EdgeType("D-Q", "D", "Q", _pairs(labels, "doc_id", "quality")),
        EdgeType("D-X", "D", "X", _pairs(labels, "doc_id", "toxic")),
    ]
    return TypedNetwork("corpus", spark, {n.name: n for n in nodes}, edges, keep=keep)


def vectors(spark: SparkSession, folder: str, keep: bool = False) -> TypedNetwork:
    """Vectors with their labels."""
    v = read_table(spark, folder, "embeddings").select("vec_id", "label")
    nodes = [NodeType("V", _keyed(v, "vec_id"), key="vec_id"), NodeType("A", v.select(F.col("label").cast("long").alias("id")).distinct())]
    return TypedNetwork("vectors", spark, {n.name: n for n in nodes}, [EdgeType("V-A", "V", "A", _pairs(v, "vec_id", "label"))], keep=keep)


NETWORKS = {"commerce": commerce, "activity": activity, "corpus": corpus, "vectors": vectors}


def from_tables(spark: SparkSession, folder: str, name: str, keep: bool = False) -> TypedNetwork:
    return NETWORKS[name](spark, folder, keep)
