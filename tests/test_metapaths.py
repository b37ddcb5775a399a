from __future__ import annotations

import random

import numpy as np
import pytest

from pathloom.functions.workload import fixed_30, generate_workload, mine_overlaps, workload_df
from pathloom import experiments as X
from pathloom.operators.backends import operand, operand_stats
from pathloom.operators.engine import CACHES, TraversalEngine, engine, evaluate, evaluate_dense, evaluate_operands, lower, run_uncached, traversal
from pathloom.operators import matrix
from pathloom.operators.matrix import hinted, multiply, multiply_skewed, operations, squared, summary, transposed
from pathloom.operators.memory import MemoryBackend, in_memory
from pathloom.plans.cost import CostCoefficients, MatrixStats, dense_cost, fit_coefficients, sparse_cost, uniform_density
from pathloom.plans.overlap import SubpathIndex, built, infixes, prefixes
from pathloom.plans.planner import ChainPlanner, Known, all_orders, order_cost
from pathloom.plans.policies import LruPolicy, SizeCostPolicy, dependency_policy
from pathloom.plans.query import parse_path
from pathloom.sources.networks import EdgeType, NodeType, TypedNetwork, commerce, from_property_graph
from pathloom.sources.storage import LOG_SCHEMA, read_workload, typed_log
from pathloom.streaming.log import overlap_counts, run_stream

SMALL = "/root/testdata/sf0.001"
AP = [(1, 1), (1, 2), (1, 3), (2, 2), (2, 3), (3, 3), (3, 4), (4, 5)]
PT = [(1, 1), (2, 1), (2, 2), (3, 1), (3, 2), (4, 3), (5, 3)]
PV = [(1, 1), (2, 1), (3, 2), (4, 2), (5, 1)]
YEARS = [(1, 2018), (2, 2021), (3, 2022), (4, 2019), (5, 2023)]


@pytest.fixture(scope="module")
def toy(spark):
    node = lambda k, n: NodeType(k, spark.createDataFrame([(i,) for i in range(1, n + 1)], "id long"))
    papers = NodeType("P", spark.createDataFrame(YEARS, "id long, year int"))
    edge = lambda name, rows: EdgeType(name, name[0], name[2], spark.createDataFrame(rows, "src long, dst long"))
    return TypedNetwork("toy", spark, {"A": node("A", 4), "P": papers, "T": node("T", 3), "V": node("V", 2)}, [edge("A-P", AP), edge("P-T", PT), edge("P-V", PV)])


@pytest.fixture(scope="module")
def net(spark):
    return commerce(spark, SMALL)


def dense(df, m, n):
    cells = {(r["src"], r["dst"]): r["n"] for r in df.collect()}
    return [[cells.get((i, j), 0) for j in range(1, n + 1)] for i in range(1, m + 1)]


TOY = [
    ("A-P-T", 4, 3, [[3, 2, 0], [2, 2, 0], [1, 1, 1], [0, 0, 1]]),
    ("A-P-T {P.year>2020}", 4, 3, [[2, 2, 0], [2, 2, 0], [1, 1, 0], [0, 0, 1]]),
    ("A-P-V", 4, 2, [[2, 1], [1, 1], [0, 2], [1, 0]]),
    ("T-P-T", 3, 3, [[3, 2, 0], [2, 2, 0], [0, 0, 2]]),
    ("A-P-T-P-A", 4, 4, [[13, 10, 5, 0], [10, 8, 4, 0], [5, 4, 3, 1], [0, 0, 1, 1]]),
    ("A-P-T-P-A {P.year>2020}", 4, 4, [[8, 8, 4, 0], [8, 8, 4, 0], [4, 4, 2, 0], [0, 0, 0, 1]]),
]


@pytest.mark.parametrize("path,m,n,want", TOY)
def test_toy_answers_of_all_evaluators(toy, path, m, n, want):
    q = parse_path(path, toy)
    for kind in ("left", "right", "dense", "sparse"):
        assert dense(evaluate(toy, q, ChainPlanner(kind)), m, n) == want
    assert dense(traversal(toy, q), m, n) == want
    assert dense(evaluate_operands(toy, q), m, n) == want
    assert dense(evaluate_dense(toy, q), m, n) == want
    for order in all_orders(0, len(q) - 1):
        assert dense(_by_order(toy, q, order), m, n) == want


def _by_order(net, q, order):
    if isinstance(order[0], int):
        return operand(net, q, order[0])
    return multiply(_by_order(net, q, order[0]), _by_order(net, q, order[1]))


def test_parsing():
    q = parse_path("O -[next]-> O - P {O@0.o_totalprice > 5; P.p_size=3}")
    assert q.types == ("O", "O", "P") and q.edges == ("next", None)
    assert q.constraints == ((0, "o_totalprice>5"), (2, "p_size=3"))
    assert q.key(1, 2) == ((1, "p_size=3"),) and q.symbols == ("O", "[next]O", "P")
    for bad in ("C", "C-", "C-O {X.a=1}", "C--O"):
        with pytest.raises(ValueError):
            parse_path(bad)


def test_steps_are_checked(net):
    with pytest.raises(KeyError):
        parse_path("C-P", net)


def test_costs():
    assert dense_cost(4, 5, 5) + dense_cost(4, 5, 3) == 160 and dense_cost(5, 5, 3) + dense_cost(4, 5, 3) == 135
    assert uniform_density(0.5, 0.5, 2) == pytest.approx(1 - 0.75**2)
    assert uniform_density(0, 1, 5) == 0 and uniform_density(1, 1, 5) == 1
    x = MatrixStats(10, 20, 50)
    assert sparse_cost(x, MatrixStats(20, 5, 10), MatrixStats(10, 5, 20)) == pytest.approx(50 + 50 * 10 / 20 + 20)
    c = fit_coefficients([(1, 0, 0, 2.0), (0, 1, 0, 3.0), (0, 0, 1, 4.0), (1, 1, 1, 9.0)])
    assert (c.alpha, c.beta, c.gamma) == pytest.approx((2, 3, 4))


def test_dynamic_program_finds_the_least_cost(net):
    for path in ("C-O-P-B", "N-C-O-P-Y", "G-C-O-P-S-N"):
        stats = operand_stats(net, parse_path(path, net))
        for planner in (ChainPlanner("dense"), ChainPlanner("sparse"), ChainPlanner("sparse", CostCoefficients(3, 0.1, 5))):
            assert planner.plan(stats).cost == pytest.approx(min(order_cost(o, stats, planner)[0] for o in all_orders(0, len(stats))))


def test_known_spans_are_used(net):
    q = parse_path("N-C-O-P-Y", net)
    stats = operand_stats(net, q)
    plan = ChainPlanner().plan(stats, {(1, 3): Known(100, 0, True)})
    assert "*13" in plan.order()
    assert ChainPlanner().plan(stats, {(0, 4): Known(10, 0, True)}).order() == "*04"


def test_overlap_index():
    index = SubpathIndex()
    for p in ("G-C-O-P", "N-C-O-P-B", "C-O-P-Y"):
        index.insert(parse_path(p))
    assert {"".join(p): x.f for p, x in index.internal()} == {"COP": 3, "OP": 3, "P": 3}
    assert index.space_report()["leaves"] == 13
    assert index.find(("C", "O")) is None and index.find(("Z",)) is None
    index.insert(parse_path("C-O-P-Y-P"))
    assert {"".join(p): x.f for p, x in index.internal()} == {"COP": 4, "OP": 4, "P": 5, "COPY": 2, "OPY": 2, "PY": 2, "Y": 2}
    index.insert(parse_path("G-C-O-P"))
    r = index.space_report()
    assert r["leaves"] == 22 and r["internal"] + r["leaves"] <= r["bound"]


def test_counts_by_constraint_sum_to_the_frequency(net):
    index = SubpathIndex()
    for q in fixed_30(net):
        index.insert(q)
    for path, x in index.internal():
        assert sum(x.keys.values()) == x.f, path


def test_predicates_have_one_spelling(net):
    keys = {parse_path("C-O-P", net, {0: c}).key(0, 2) for c in ("C=7", "C = 7", "id = 7", "c_custkey=  7", "id=07")}
    assert keys == {((0, "id = 7"),)}
    odd = parse_path("C-O", net, {0: "c_mktsegment = 'a  & 1:b = 2'"})
    assert odd.key(0, 1) == ((0, "c_mktsegment='a  & 1:b = 2'"),)


def test_dependence():
    cop = ("C", "O", "P")
    key = (("C", "O", "P", "B"), ((0, "id = 7"), (3, "x")))
    assert (cop, ((0, "id = 7"),)) in prefixes(key) and (cop, ()) not in prefixes(key) and key not in prefixes(key)
    assert (("P", "B"), ((1, "x"),)) in infixes(key) and (("P", "B"), ((1, "x"),)) not in prefixes(key)


def test_linear_construction_gives_the_same_index(net):
    rng = random.Random(4)
    logs = [[parse_path(p) for p in ("G-C-O-P", "N-C-O-P-B", "C-O-P-Y", "C-O-P-Y-P", "G-C-O-P")], fixed_30(net)]
    logs += [[parse_path("-".join(rng.choice("AB") for _ in range(rng.randint(2, 7)))) for _ in range(rng.randint(1, 12))] for _ in range(60)]
    logs.append([parse_path(p, net, {a: c}) for _, p, a, c in generate_workload(net, 200, seed=1)])
    for queries in logs:
        one, other = SubpathIndex(), built(queries)
        for q in queries:
            one.insert(q)
        shape = lambda x: sorted((path, n.f, tuple(sorted(n.keys.items()))) for path, n in x.internal())
        assert shape(one) == shape(other) and one.space_report() == other.space_report()


def test_a_horizon_forgets_older_queries(net):
    queries = fixed_30(net)
    short = SubpathIndex(horizon=7)
    for q in queries:
        short.insert(q)
    fresh = SubpathIndex()
    for q in queries[-7:]:
        fresh.insert(q)
    shape = lambda x: sorted((path, n.f, tuple(sorted(n.keys.items()))) for path, n in x.internal())
    assert shape(short) == shape(fresh) and short.leaves == fresh.leaves


REQUESTS = [("COP", 12, 4), ("COPY", 6, 3), ("OPS", 20, 5), ("COP", 12, 4), ("COPY", 6, 3), ("OPS", 20, 5), ("COP", 12, 4)]


def test_cache_traces():
    run = lambda p: [p.request(*r).evicted for r in REQUESTS]
    assert run(LruPolicy(10)) == [[], [], ["COP"], ["COPY"], ["OPS"], ["COP"], ["COPY"]]
    plain = SizeCostPolicy(10)
    assert run(plain) == [[], [], ["COPY"], [], ["OPS"], ["COP"], ["COPY"]]
    assert (plain.utility("OPS"), plain.utility("COP")) == (16, 19)
    aware = dependency_policy(10, lambda k: [k[:n] for n in range(1, len(k))])
    steps = []
    for r in REQUESTS:
        aware.request(*r)
        steps.append({k: (e.cost, aware.utility(k)) for k, e in aware.items.items()})
    assert steps[5]["COPY"] == (18, 18) and steps[6] == {"COPY": (6, 10), "COP": (12, 25)}


def test_oversize_items_are_refused():
    p = LruPolicy(100, 0.8)
    assert not p.request("a", 1, 81).stored and p.request("b", 1, 80).stored and p.rejected == 1


def test_engines_agree(spark, net):
    queries = fixed_30(net)[:8]
    want = {tuple(r) for r in run_uncached(net, queries, "traversal").collect()}
    for name in ("all_products", "reference"):
        assert {tuple(r) for r in engine(net, name, 20_000).run(queries).collect()} == want, name


def test_generated_workloads_have_the_same_answers_under_all_engines(net):
    small = in_memory(net)
    row = dict(network="n", setting="s", value=0.0, workload=3, cache_ratio=0.2, restart_p=0.08, alpha=0.0)
    found = {name: list(X.run_of(small, {**row, "engine": name})) for name in CACHES}
    answers = {name: [r[-2:] for r in rows] for name, rows in found.items()}
    assert all(a == answers["sparse"] for a in answers.values())
    assert sum(r[0] for r in answers["sparse"]) > 0
    operations = {name: sum(r[18] for r in rows) for name, rows in found.items()}
    assert operations["reference"] < operations["sparse"]
    assert sum(r[14] for r in found["reference"]) > 0


def test_memory_answers_are_the_tables(net):
    queries = fixed_30(net)[:10]
    small = in_memory(net, queries)
    e = engine(small, "reference", 20_000, backend=MemoryBackend(small))
    got = [(i, *e.summary_of(q, i)) for i, q in enumerate(queries)]
    assert got == [tuple(r) for r in run_uncached(net, queries, "sparse").orderBy("pos").collect()]


def test_spans_hold_what_their_own_predicates_say(net):
    """A span that ends at a predicate inside one query answers a query that ends there."""
    one, two = parse_path("C-O-P-B", net, {2: "id = 5"}), parse_path("C-O-P", net, {2: "id = 5"})
    small = in_memory(net)
    e = engine(small, "all_products", 1e9, backend=MemoryBackend(small))
    for q in (one, two, one):
        got = e.summary_of(q, 0)
        assert got == tuple(summary(evaluate(net, q)).first())


def test_evicted_tables_are_deleted(net, spark):
    e = engine(net, "reference", 3000)
    queries = fixed_30(net)[:8]
    for i, q in enumerate(queries):
        summary(e.run_one(q, i)).first()
    paths = [f for t in e.tables.values() for f in t.inputFiles()]
    for x in [x for part in e.going for x in part]:
        e.backend.drop(x)
    hadoop = spark._jvm.org.apache.hadoop.fs
    there = lambda f: hadoop.Path(f).getFileSystem(spark._jsc.hadoopConfiguration()).exists(hadoop.Path(f))
    assert sum(m.evictions + m.rejected for m in e.metrics) > 0 and all(map(there, paths))


def test_traversals_reuse_their_statements(net):
    t = TraversalEngine(net)
    for key in (3, 4, 5):
        q = parse_path("C-O-P", net, {0: f"id = {key}"})
        assert sorted(map(tuple, t.run_one(q).collect())) == sorted(map(tuple, evaluate(net, q).collect()))
    assert t.reused == 2 and len(t.statements) == 1
    t.close()


def test_products_dealt_over_cells(net):
    x, y = net.adjacency("P", "S"), net.adjacency("S", "P")
    want = sorted(map(tuple, multiply(x, y).collect()))
    assert sorted(map(tuple, multiply(x, y, operations=1e8, middle=3).collect())) == want
    assert sorted(map(tuple, multiply_skewed(x, y, heavy=20).collect())) == want
    assert sorted(map(tuple, squared(x, operations=1e8, middle=3).collect())) == want == sorted(map(tuple, multiply(x, transposed(x)).collect()))


def test_costs_given_back_are_what_was_taken():
    """Base costs return when ancestors come and go."""
    p = dependency_policy(100, lambda k: [k[:n] for n in range(1, len(k))])
    p.request("abc", 30, 10)
    p.request("ab", 12, 10)
    assert p.items["abc"].cost == 18
    p.forget("ab")
    assert p.items["abc"].cost == 30
    near = dependency_policy(100, lambda k: [k[:n] for n in range(1, len(k))], nearest=True)
    for key, full in (("abcd", 40), ("ab", 12), ("abc", 30)):
        near.request(key, full, 10, full)
    assert (near.items["abcd"].cost, near.items["abc"].cost) == (10, 18)
    near.forget("abc")
    assert near.items["abcd"].cost == 28


def test_reference_computes_fewer_products(net):
    queries = fixed_30(net)
    queries = queries + queries[::-1]
    small, runs = in_memory(net, queries), {}
    for name in ("sparse", "reference"):
        e = engine(small, name, backend=MemoryBackend(small))
        for i, q in enumerate(queries):
            e.run_one(q, i)
        runs[name] = sum(m.products for m in e.metrics)
    assert runs["reference"] < 0.7 * runs["sparse"]


def test_operations_are_counted_from_degrees(toy):
    x, y = toy.adjacency("A", "P"), toy.adjacency("P", "T")
    assert operations(x, y).first()[0] == sum(1 for a in AP for b in PT if a[1] == b[0])


def test_generated_workloads(net):
    rows = generate_workload(net, 200, restart_p=0.1, seed=1)
    assert rows == generate_workload(net, 200, restart_p=0.1, seed=1) != generate_workload(net, 200, restart_p=0.1, seed=2)
    assert 8 <= len({r[0] for r in rows}) <= 40
    for _, path, at, predicate in rows:
        q = parse_path(path, net, {at: predicate})
        assert 3 <= len(q) <= 5
        (found,) = (c for _, c in q.constraints)
        assert not net.selection(q.types[at], found).isEmpty() if path == rows[0][1] else True
    keys = net.keys_at("O", list(range(40)), 3)
    present = {r["id"] for r in net.nodes["O"].df.select("id").collect()}
    assert len(set(keys.values())) == 40 and set(keys.values()) <= present and keys != net.keys_at("O", list(range(40)), 4)
    zipf = generate_workload(net, 200, dist="zipf", alpha=2, seed=1)
    assert len({r[1] for r in zipf}) < len({r[1] for r in rows})


def test_mined_overlaps_match_the_index(spark):
    paths = ["G-C-O-P", "N-C-O-P-B", "C-O-P-Y"]
    mined = {r["sub_path"]: r["f"] for r in mine_overlaps(workload_df(spark, [(0, p, 0, "") for p in paths])).collect()}
    assert mined == {"C-O": 3, "O-P": 3, "C-O-P": 3}


def test_core_split_shrinks(net):
    q = parse_path("C-O-P", net)
    sizes = [summary(evaluate(net.core_split("O", p), q)).first()["sum_n"] for p in (60, 80, 100)]
    assert sizes[0] < sizes[1] < sizes[2] == summary(evaluate(net, q)).first()["sum_n"]


def test_property_graphs_become_networks(spark):
    v = spark.createDataFrame([(1, "A"), (2, "B"), (3, "B")], "id long, type string")
    e = spark.createDataFrame([(1, 2, "x"), (1, 3, "x")], "src long, dst long, type string")
    g = from_property_graph("g", v, e)
    assert {tuple(r) for r in g.infer_schema().collect()} == {("A", "x", "B", 2)}
    assert evaluate(g, parse_path("B-[x]->A-[x]->B", g)).count() == 4


def test_streamed_logs_are_answered(spark, net, tmp_path):
    rows = [(i, 0, q.path, {str(p): c for p, c in q.constraints}) for i, q in enumerate(fixed_30()[:4])]
    spark.createDataFrame(rows, LOG_SCHEMA).coalesce(1).write.json(str(tmp_path / "log"))
    assert read_workload(spark, str(tmp_path / "log")).count() == 4
    log = typed_log(spark.readStream.schema(LOG_SCHEMA).json(str(tmp_path / "log")))
    got = []
    run_stream(log, engine(net, "reference"), str(tmp_path / "ck"), lambda df, n: got.extend(map(tuple, df.collect()))).processAllAvailable()
    for s in spark.streams.active:
        s.stop()
    assert got == [tuple(r) for r in run_uncached(net, fixed_30()[:4], "sparse").orderBy("pos").collect()]


def test_windows_over_a_log(spark):
    log = spark.sql("SELECT timestamp'2024-01-01 00:00:00' + make_interval(0,0,0,0,0,id * 4,0) AS ts, 'U-E-T' AS path FROM range(6)")
    tumbling = {(r["sub_path"], r["f"]) for r in overlap_counts(log, "8 minutes").collect()}
    assert tumbling == {("U-E", 2), ("E-T", 2), ("U-E-T", 2)}
    assert {r["f"] for r in overlap_counts(log, "8 minutes", slide="4 minutes").collect()} == {1, 2}
    assert {r["f"] for r in overlap_counts(log, "", gap="5 minutes").collect()} == {6}


def test_plans_push_filters_and_prune_columns(net, spark, capsys):
    q = parse_path("C-O-P", net, {0: "C=7"})
    evaluate(net, q).explain("formatted")
    text = capsys.readouterr().out
    assert "EqualTo(o_custkey,7)" in text and "o_orderdate" not in text and "CartesianProduct" not in text


def test_lowered_plans_have_no_python(net):
    q = parse_path("N-C-O-P", net)
    df = lower(net, q, ChainPlanner().plan(operand_stats(net, q)))
    assert "Python" not in df._jdf.queryExecution().toString()


def test_tables_need_a_shared_folder_on_a_cluster():
    from types import SimpleNamespace

    from pathloom.sources.storage import shared_dir

    def session(master, folder=None):
        context = SimpleNamespace(master=master, folder=folder)
        context.getCheckpointDir, context.setCheckpointDir = lambda: context.folder, lambda f: setattr(context, "folder", f)
        return SimpleNamespace(sparkContext=context, conf={})

    assert shared_dir(session("spark://host:7077", "/shared")) == "/shared"
    for master in ("spark://host:7077", "yarn", "local-cluster[3,1,1024]"):
        with pytest.raises(ValueError):
            shared_dir(session(master))
    alone = session("local[2]")
    assert shared_dir(alone) == shared_dir(alone)


def test_utility_policy_evicts_the_least_after_evictions():
    """A key that comes again is not judged by what it was worth before it was evicted."""
    rng = np.random.default_rng(3)
    made = {"U-E-T": ["U-E"], "U-E-K": ["U-E"]}
    cost = {"U-E": 4.0, "U-E-T": 6.0, "U-E-K": 8.0, "E-K": 5.0, "E-D": 3.0}
    for _ in range(30):
        p = dependency_policy(2, lambda k: made.get(k, []))
        for key in rng.choice(list(cost), 60):
            least = min(p.items, key=lambda k: (p.utility(k), p.items[k].order)) if len(p.items) == 2 and key not in p else None
            assert p.request(key, cost[key], 1).evicted == ([least] if least else [])


def test_only_small_sides_are_broadcast(spark):
    x = spark.range(5).selectExpr("id AS src", "id AS dst", "1L AS n")
    plan = lambda entries: multiply(x, hinted(x, "broadcast", entries))._jdf.queryExecution().analyzed().toString()
    assert "broadcast" in plan(1_000_000) and "broadcast" not in plan(36_000_000)


def test_dense_tiles_of_large_matrices(spark, monkeypatch):
    """Matrices of more cells than rows may hold are multiplied tile by tile, with the same result."""
    net = commerce(spark, "/root/testdata/sf0.001")
    q = parse_path("B-P-S-N", net)
    want = sorted(map(tuple, evaluate(net, q).collect()))
    monkeypatch.setattr(matrix, "TILE", 7)
    monkeypatch.setattr(matrix, "TILE_MIDDLE", 60)
    monkeypatch.setattr(matrix, "STRIP", 13)
    assert sorted(map(tuple, evaluate_dense(net, q, 10).collect())) == want
