"""What large tables need: networks read once and lean, work in bounded pieces."""

from __future__ import annotations

import pickle

import numpy as np
import pytest

from pathloom import queries as Q
from pathloom import queries_workloads as QW
from pathloom.functions.workload import fixed_30
from pathloom.operators.memory import TooLarge, in_memory
from pathloom.plans.query import parse_path
from pathloom.sources.networks import EdgeType, NodeType, TypedNetwork, commerce

SMALL = "/root/testdata/sf0.001"


def two_types(spark, edges, n=4):
    node = lambda k: NodeType(k, spark.range(1, n + 1))
    return TypedNetwork("two", spark, {"A": node("A"), "B": node("B")}, [EdgeType("A-B", "A", "B", spark.createDataFrame(edges, "src long, dst long"))])


def test_arrays_put_parallel_edges_together(spark):
    net = two_types(spark, [(1, 2), (3, 1), (2, 4), *[(1, 2)] * 6])
    x = in_memory(net).matrices["A", "B", None]
    assert list(zip(x.src.tolist(), x.dst.tolist(), x.n.tolist(), strict=True)) == [(0, 1, 1), (1, 3, 1), (2, 0, 1)] and x.binary
    y = in_memory(net).matrices["B", "A", None]
    assert list(zip(y.src.tolist(), y.dst.tolist(), strict=True)) == [(0, 2), (1, 0), (3, 1)]
    assert in_memory(net, most=8).matrices["A", "B", None].nnz == 3  # nine rows, but three edges
    with pytest.raises(TooLarge):
        in_memory(two_types(spark, [(i % 4 + 1, i // 4 + 1) for i in range(16)]), most=9)
    net.weight = "multiplicity"
    for most in (100, 8):  # counted here, or by Spark
        assert in_memory(net, most=most).matrices["A", "B", None].n.tolist() == [7, 1, 1]


def test_arrays_leave_out_relations_that_no_query_walks(spark):
    net = commerce(spark, SMALL)
    queries = fixed_30(net)[:1]
    small = in_memory(net, queries, used=True)
    assert set(small.matrices) == {("C", "O", None), ("O", "C", None), ("O", "P", None), ("P", "O", None)}
    assert set(small.nodes) == set(net.nodes)


def test_workload_is_read_once_for_all_engines_and_goes_to_tables_where_arrays_are_too_large(spark, monkeypatch):
    reads = []
    monkeypatch.setattr(QW, "in_memory", lambda *a, **k: reads.append(1) or in_memory(*a, **k))
    want = sorted(map(tuple, Q.queries()["hit_rates"](spark, SMALL).collect()))
    assert len(reads) == 1
    monkeypatch.setattr(QW.W, "fixed_30", lambda net=None: fixed_30(net)[:3])
    few = sorted(map(tuple, Q.queries()["engine_reverse"](spark, SMALL).collect()))
    monkeypatch.setattr(QW, "MOST_ROWS", 10)
    assert sorted(map(tuple, Q.queries()["engine_reverse"](spark, SMALL).collect())) == few
    assert want == [("final_cache", 0.5), ("sparse", 0.0)]


def test_large_squares_are_made_in_tiles(spark, monkeypatch):
    from pathloom.operators import engine, tiles

    net = commerce(spark, SMALL)
    for path in ("P-S-P", "P-O-P", "C-O-P-B-P-O-C"):
        q = parse_path(path, net)
        want, whole = (sorted(map(tuple, f(net, q).collect())) for f in (engine.evaluate, engine.evaluate_summary))
        with monkeypatch.context() as m:
            m.setattr(tiles, "LEAST_OPERATIONS", 0)
            m.setattr(tiles, "LEAST_RATIO", 0)
            m.setattr(tiles, "TILE_ENTRIES", 3000)
            for full in (0, 1e9):
                m.setattr(tiles, "FULL_CELLS", full)
                found = engine.evaluate(net, q)
                assert "FlatMapGroupsInArrow" in found._jdf.queryExecution().toString()
                assert sorted(map(tuple, found.collect())) == want
                assert sorted(map(tuple, engine.evaluate_summary(net, q).collect())) == whole == [(len(want), sum(r[2] for r in want), max(r[2] for r in want))]


def test_products_of_large_results_are_counted_without_being_kept(spark, monkeypatch):
    from pathloom.operators import memory as M

    net = in_memory(commerce(spark, SMALL))
    x, y = net.matrices["P", "O", None], net.matrices["O", "P", None]
    want, total = M.product(x, y)
    sent = pickle.loads(pickle.dumps(x))
    assert sent.binary and len(pickle.dumps(x)) < 9 * x.nnz + 1000  # ones are neither sent nor forgotten
    monkeypatch.setattr(M, "KEPT_BYTES", 1000)
    z, again = M.product(sent, y)
    assert isinstance(z, M.Large) and "src" not in vars(z) and again == total
    assert M.MemoryBackend(net).summary(z) == (z.nnz, int(want.n.sum()), int(want.n.max())) == M.MemoryBackend(net).summary(want)
    assert all((getattr(z, c) == getattr(want, c)).all() for c in ("src", "dst", "n"))


def test_engines_of_one_workload_make_each_product_once(spark, monkeypatch):
    from pathloom import experiments as X
    from pathloom.operators import memory as M

    net = in_memory(commerce(spark, SMALL))
    rows = [{"network": "commerce", "split": 100, "setting": "default", "value": 0.0, "engine": e, "workload": 0, "cache_ratio": 3.0, "restart_p": 0.08, "alpha": 0.0} for e in ("sparse", "reference", "tree_lru")]
    apart = [[r[:7] + r[9:] for r in X.run_of(net, row, 30)] for row in rows]
    made = []
    monkeypatch.setattr(M, "product", lambda x, y, f=M.product: made.append(1) or f(x, y))
    found = list(X.runs_of(net, rows, 30))
    for row, want in zip(rows, apart, strict=True):
        assert [r[:7] + r[9:] for r in found if r[3] == row["engine"]] == want
    assert len(made) < sum(r[9] for r in found) / 2 and all(r[8] > 0 for r in found)


def test_keys_are_looked_up_as_a_search_finds_them(monkeypatch):
    from pathloom.operators import memory as M

    ids, searched = np.array([3, 5, 6, 9, 14]), []
    monkeypatch.setattr(M.np, "searchsorted", lambda *a, f=np.searchsorted: searched.append(1) or f(*a))
    for keys in ([3, 14, 6, 9, 5, 3], [4, 7, 13, 10]):
        assert M._places(ids, np.array(keys)).tolist() == [sum(i < k for i in ids) for k in keys]
    assert not searched
    assert M._places(ids, np.array([0, 20, 6])).tolist() == [0, 5, 2] and M._places(np.array([1, 10**9]), np.array([10**9])).tolist() == [1]
    assert M._places(ids[:0], ids[:0]).tolist() == [] and len(searched) == 3


def test_rows_of_the_next_relation_are_read_beside_the_arrays_of_one(spark, monkeypatch):
    import threading

    from pathloom.operators import memory as M

    names, want = set(), in_memory(commerce(spark, SMALL))
    kind = type(spark.range(1))
    monkeypatch.setattr(kind, "toArrow", lambda self, f=kind.toArrow: names.add(threading.current_thread().name) or f(self))
    net = M.in_memory(commerce(spark, SMALL))
    assert len(names) > 2 and threading.main_thread().name not in names
    assert set(net.matrices) == set(want.matrices) and all((net.matrices[k].src == x.src).all() and (net.matrices[k].dst == x.dst).all() for k, x in want.matrices.items())
    assert M._rows([spark.range(3), spark.range(4)]) == 7 and M._rows([]) == 0


def test_engines_over_the_fixed_workload_make_each_product_once(spark, monkeypatch):
    from pathloom.operators import memory as M

    made = []
    monkeypatch.setattr(M, "product", lambda x, y, f=M.product: made.append(1) or f(x, y))
    rows = Q.queries()["engine_metrics_all"](spark, SMALL).collect()
    asked = sum(r["products"] for r in rows if r["engine"] == "sparse")
    assert sum(r["products"] for r in rows) > 3 * asked and len(made) <= 2 * asked
    made.clear()
    rows = Q.queries()["engine_metrics"](spark, SMALL).collect()
    assert len(made) <= asked and sum(r["products"] for r in rows) == 3 * asked


def test_only_met_rows_of_a_result_that_was_not_kept_are_made_again(spark, monkeypatch):
    from pathloom.operators import memory as M

    net = in_memory(commerce(spark, SMALL))
    x, y = net.matrices["P", "O", None], net.matrices["O", "P", None]
    few, whole = x.picked(x.src < 2), M.product(y, x)[0]
    want, total = M.product(few, whole)
    monkeypatch.setattr(M, "KEPT_BYTES", 50_000)
    z = M.product(y, x)[0]
    found, again = M.product(few, z)
    assert isinstance(z, M.Large) and "src" not in vars(z) and again == total
    assert all((getattr(found, c) == getattr(want, c)).all() for c in ("src", "dst", "n"))


def test_samples_of_products_are_those_of_one_thread(spark, monkeypatch):
    from pathloom import experiments as X

    found = {}
    for many in (1, 4):
        monkeypatch.setattr(X, "SAMPLERS", many)
        found[many] = {name: [s[:3] for s in samples] for name, samples in X.product_samples(spark, SMALL, 20).items()}
    assert found[1] == found[4] and set(found[1]) == {"commerce", "activity"} and all(found[1].values())


def test_dense_order_does_not_make_whole_products_that_a_selection_cuts(spark, monkeypatch):
    from pathloom.functions.workload import FIXED_30
    from pathloom.operators import engine as E
    from pathloom.operators.matrix import multiply, summary
    from pathloom.plans.planner import ChainPlanner

    net = commerce(spark, SMALL)
    monkeypatch.setattr(E, "FEW_REACHED", 0.5)
    made, cut_by = [], []
    monkeypatch.setattr("pathloom.operators.backends.multiply", lambda x, y, **k: made.append((x, y)) or multiply(x, y, **k))
    for i in (3, 18, 28):  # a selection at the start, one that reaches too much, one that reaches the second half
        path, place, predicate = FIXED_30[i][1:]
        q = parse_path(path, net, {place: predicate})
        made.clear()
        found = summary(E.evaluate(net, q, ChainPlanner("dense"))).first()
        assert found == summary(E.evaluate(net, q)).first()
        inner = min(x.count() for x, _ in made[:2])
        cut_by.append(inner)
        plan = ChainPlanner("dense").plan(E.operand_stats(net, q))
        assert bool(E.cut(net, q, plan, E.operand_stats(net, q))) == (i != 18)
    assert cut_by[0] < net.edge("O", "P")[0].df.count() / 20
    three = E.run_uncached(net, [parse_path(FIXED_30[i][1], net, {FIXED_30[i][2]: FIXED_30[i][3]}) for i in (0, 3, 28)], "dense")
    assert "Aggregate" not in three._jdf.queryExecution().toString() and three.count() == 3


def test_spread_of_estimates_is_over_all_queries(spark, monkeypatch):
    from pathloom import experiments as X

    asked = []
    monkeypatch.setattr(X, "ABLATION", 8)
    monkeypatch.setattr(X, "ablation", lambda spark, folder, n, f=X.ablation: asked.append(n) or f(spark, folder, n))
    assert Q.queries()["estimate_spread"](spark, SMALL).count() == 2 and asked == [8]


def test_dense_operations_beyond_a_long_are_given_whole(spark, monkeypatch):
    small = Q.queries()["dense_ops_example"](spark, SMALL)
    want = {r["plan"]: r["ops"] for r in small.collect()}
    assert dict(small.dtypes)["ops"] == "bigint"
    monkeypatch.setattr(Q, "dense_cost", lambda m, n, k, f=Q.dense_cost: f(m, n, k) << 50)
    large = {r["plan"]: int(r["ops"]) for r in Q.queries()["dense_ops_example"](spark, SMALL).collect()}
    assert large == {k: v << 50 for k, v in want.items()} and max(large.values()) > Q.MOST_LONG


def test_engines_over_tables_make_each_product_once(spark, monkeypatch):
    from pathloom.operators import backends as B

    counted = lambda rows: sorted((r["engine"], r["pos"], r["products"], r["whole_hits"], r["offers"], r["evictions"], r["rejected"], r["resident_bytes"]) for r in rows)
    monkeypatch.setattr(QW.W, "fixed_30", lambda net=None: [*fixed_30(net)[:8], parse_path("C-O-P", net, {0: "C=-1"})])
    want = Q.queries()["engine_metrics_all"](spark, SMALL).collect()
    monkeypatch.setattr(QW, "MOST_ROWS", 10)
    made, answers, gone = [], {}, []
    monkeypatch.setattr(B, "multiply", lambda x, y, f=B.multiply, **k: made.append(1) or f(x, y, **k))
    monkeypatch.setattr(B, "dropped", lambda x, f=B.dropped: gone.append(1) or f(x))
    monkeypatch.setattr(B.SharedTableBackend, "summary", lambda self, x, f=B.SharedTableBackend.summary: answers.setdefault(id(self), []).append(f(self, x)) or answers[id(self)][-1])
    rows = Q.queries()["engine_metrics_all"](spark, SMALL).collect()
    assert counted(rows) == counted(want) and len(made) == len(gone) < sum(r["products"] for r in rows) / 3
    assert all(r["exec_seconds"] > 0 for r in rows if r["products"])
    found = commerce(spark, SMALL)
    alone = [tuple(B.summary(B.reduce(lambda x, y: B.multiply(x, y), [B.operand(found, q, s) for s in range(len(q) - 1)])).first()) for q in QW.W.fixed_30(found)]
    assert list(answers.values()) == [alone] * 6 and alone[-1] == (0, 0, 0)


def test_large_products_over_tables_are_stored_only_for_others(spark, monkeypatch):
    from pathloom.operators import backends as B
    from pathloom.operators.engine import engine, evaluate_summary

    net, tables = commerce(spark, SMALL, keep=True), []
    q, r = parse_path("C-O-P-B", net, {1: "o_orderdate>=DATE'2001-01-01'"}), parse_path("N-C-O", net)
    want = [tuple(evaluate_summary(net, x).first()) for x in (q, r)]
    monkeypatch.setattr(B, "LARGE_BYTES", 0)
    monkeypatch.setattr(B, "stored", lambda df, label, f=B.stored: tables.append(label) or f(df, label))
    shared = B.SharedTables(most=0)
    engines = [engine(net, name, 20_000, backend=B.SharedTableBackend(net, shared), clock=shared.clock) for name in ("sparse", "all_products", "sparse")]
    for i, x in enumerate((q, r, q)):
        assert [tuple(e.summary_of(x, i)) for e in engines] == [want[i % 2]] * 3
        shared.trim()  # what is no longer known is made again
    assert 1 <= len(tables) <= 3 and all(m.exec_seconds > 0 for e in engines for m in e.metrics)
    shared.close()


def test_the_other_direction_of_a_kept_matrix_takes_no_exchange(spark, monkeypatch):
    from pathloom.sources import networks as N

    plans = []
    monkeypatch.setattr(N, "stored", lambda df, label, f=N.stored: plans.append(df._jdf.queryExecution().toString()) or f(df, label))
    net, plain = commerce(spark, SMALL, keep=True), commerce(spark, SMALL)
    for weight in ("binary", "multiplicity"):
        net.adjacency("O", "P", weight=weight)
        plans.clear()
        found = net.adjacency("P", "O", weight=weight)
        assert sorted(map(tuple, found.collect())) == sorted(map(tuple, plain.adjacency("P", "O", weight=weight).collect()))
        assert len(plans) == 1 and "Exchange" not in plans[0] and "lineitem" not in plans[0]
    assert net.step_stats("P", "O").nnz == net.step_stats("O", "P").nnz
