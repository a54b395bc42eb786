"""Worked examples, invariants, edge cases and an independent shortest-path search."""

import heapq
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from skewgraph import queries as q
from skewgraph.functions import loads as ld
from skewgraph.functions import measures as ms
from skewgraph.graph import Graph, to_edges
from skewgraph.operators import programs, scan
from skewgraph.operators.strategies import PLANS, Front, Options, blocks, split_edges, split_map
from skewgraph.plans import chain, engine
from skewgraph.views import VIEWS

SF = "/root/testdata/sf0.001"


def rows(frame):
    return sorted(map(tuple, frame.collect()))


def graph(spark, edges):
    return Graph.of(spark.createDataFrame(edges, "src long, dst long, w long"))


def shortest(edges, start):
    out, best, heap = {}, {start: 0}, [(0, start)]
    for s, d, w in edges:
        out.setdefault(s, []).append((d, w))
    while heap:
        at, node = heapq.heappop(heap)
        if at > best[node]:
            continue
        for d, w in out.get(node, []):
            if at + w < best.get(d, 1 << 60):
                best[d] = at + w
                heapq.heappush(heap, (at + w, d))
    return best


def test_worked_examples(spark):
    deg = lambda *pairs: spark.createDataFrame(pairs, "node long, deg long")
    front = lambda *pairs: deg(*pairs).withColumn("superstep", F.lit(1).cast("long"))
    assert rows(blocks(deg((1, 5), (8, 7)), 4).select("worker", "node", "offset", "len")) == [(1, 1, 0, 3), (2, 1, 3, 2), (2, 8, 0, 1), (3, 8, 1, 3), (4, 8, 4, 3)]
    assert rows(split_map(deg((8, 7)), 4)) == [(8, 0, 4), (8, 1, 3)]
    assert [tuple(r)[1:4] for r in ld.sublist_report(front((1, 5), (8, 7)), 3, 0).orderBy("launch").collect()] == [(0, 2, 6), (1, 2, 5), (2, 1, 1)]
    assert [ld.sublist_report(front((1, 100)), 5, s).count() for s in (0, 1024)] == [20, 1]


def test_examples_divide_the_lines(spark):
    per = [r["count"] for r in spark.read.parquet(f"{SF}/lineitem.parquet").groupBy("l_suppkey").count().collect()]
    total = lambda frame, c: frame.agg(F.sum(c)).first()[0]
    assert total(q.wd_blocks_example(spark, SF), "len") == total(q.udtf_frontier_blocks(spark, SF), "len") == sum(per)
    assert total(q.ns_split_example(spark, SF), "part_deg") == sum(x for x in per if x > 64)
    assert total(q.hp_sublists_example(spark, SF), "edges") == sum(per)
    assert rows(q.hp_tail_example(spark, SF)) == [(1, 1024), (-(-max(per) // 5), 0)]


@pytest.mark.parametrize("strategy", ms.STRATEGIES)
def test_shortest_paths(spark, strategy):
    edges = VIEWS["part_next"](spark, SF)
    got = engine.sssp(Graph.of(edges, page=16), [0], strategy, options=Options(4, switch_below=4)).state
    assert {r.node: r.value for r in got.collect()} == shortest([tuple(r) for r in edges.collect()], 0)


@pytest.mark.parametrize("strategy", ms.STRATEGIES)
def test_small_graphs(spark, strategy):
    edges = [(0, 1, 5), (0, 1, 2), (1, 2, 0), (2, 2, 1), (0, 3, 2), (5, 6, 1)] + [(3, 10 + i, i) for i in range(9)]
    got = engine.sssp(graph(spark, edges), [0], strategy, options=Options(30, mdt=1, switch_below=0)).state
    assert {r.node: r.value for r in got.collect()} == shortest(edges, 0)
    assert rows(engine.bfs(graph(spark, edges), [6], strategy).state.select("node", "value")) == [(6, 0)]


HUB = [(0, 1, 1)] + [(1, 10 + i, 1 + i % 3) for i in range(997)] + [(10 + i, 2000 + i, 1) for i in range(200)]


@pytest.mark.parametrize("strategy", ms.STRATEGIES)
def test_tasks_hold_what_the_strategy_decides(spark, strategy):
    workers, mdt = 4, 100
    own = Graph.of(spark.createDataFrame(HUB, "src long, dst long, w long"), page=64)
    run = engine.bfs(own, [0], strategy, options=Options(workers, mdt=mdt, switch_below=0, record=True))
    second = run.worker_loads.where("superstep = 2")
    assert second.agg(F.sum("load")).first()[0] == 997
    tasks = {r.task: r["sum(load)"] for r in second.groupBy("task").sum("load").collect()}
    workers_of = second.groupBy("launch", "task").agg(F.countDistinct("worker").alias("n")).agg(F.max("n")).first()[0]
    assert workers_of == 1
    if strategy == "BS":
        assert list(tasks.values()) == [997]
    elif strategy in ("EP", "WD"):
        assert max(tasks.values()) == -(-997 // workers) and len(tasks) == workers
    elif strategy == "NS":
        assert second.agg(F.max("load")).first()[0] <= 3 * mdt and len(tasks) == workers
    else:
        assert max(tasks.values()) <= mdt and second.select("launch").distinct().count() == 10
    assert [r["relaxations"] for r in run.rows] == [1, 997, 200] and [r["improved"] for r in run.rows] == [1, 997, 200]


@pytest.mark.parametrize(
    "strategy, more",
    [
        ("BS", {"assign": "hash"}), ("BS", {"workers": "per_node"}), ("EP", {"chunked": False}), ("EP", {"condense": "never"}), ("WD", {"place": "pages"}),
        ("HP", {"fused": False, "mdt": 3, "switch_below": 2}), ("HP", {"depth": 2, "group": 7, "mdt": 2, "switch_below": 0}), ("NS", {"mdt": 2}),
    ],
)
def test_options_keep_the_distances(spark, strategy, more):
    edges = VIEWS["part_next"](spark, SF)
    got = engine.sssp(Graph.of(edges, page=8), [0], strategy, options=Options(**({"workers": 4, "switch_below": 4} | more))).state
    assert {r.node: r.value for r in got.collect()} == shortest([tuple(r) for r in edges.collect()], 0)


def test_pushes(spark):
    own = lambda **more: engine.bfs(graph(spark, HUB), [0], "EP", options=Options(4, **more)).metrics.agg(F.sum("pushes")).first()[0]
    assert own() == 1198 and own(chunked=False) == 1197


def test_many_entries_of_nodes_are_not_broadcast(spark, monkeypatch):
    run, plans = engine.PLANS["EP"], []

    def kept(front, *more):
        work = run(front, *more)
        plans.append((front.nodes, work.rows._jdf.queryExecution().executedPlan().toString()))
        return work

    monkeypatch.setitem(engine.PLANS, "EP", kept)
    monkeypatch.setattr("skewgraph.operators.strategies.PUSHED_ROWS", 10)
    edges = [(0, i, 1) for i in range(1, 41)] + [(i, 100 + i, 1) for i in range(1, 41)]
    assert {r.node: r.value for r in engine.bfs(graph(spark, edges), [0], "EP").state.collect()} == shortest(edges, 0)
    assert [("BroadcastHashJoin" in p, n) for n, p in plans] == [(True, 1), (False, 40)]


@pytest.mark.parametrize("strategy", ms.STRATEGIES)
def test_long_searches_are_chained(spark, monkeypatch, strategy):
    edges = [(i, i + d, 1 + (i * d) % 5) for i in range(300) for d in (1, 2)] + [(0, 400 + i, 1) for i in range(30)] + [(150, 500 + i, 1) for i in range(40)]
    jobs, own = [], engine._launched
    monkeypatch.setattr(engine, "_launched", lambda *a: jobs.append(1) or own(*a))
    monkeypatch.setattr(chain, "AFTER", 2)
    monkeypatch.setattr(chain, "FRONT_EDGES", 30)
    monkeypatch.setattr(engine, "SMALL_NODES", 0 if strategy in ("WD", "NS") else 1 << 18)
    run = engine.sssp(graph(spark, edges), [0], strategy, options=Options(4, mdt=3, switch_below=1))
    assert {r.node: r.value for r in run.state.collect()} == shortest(edges, 0)
    assert len(jobs) <= 6 and run.supersteps > 100 and [r["superstep"] for r in run.rows] == list(range(1, run.supersteps + 1))


@pytest.mark.parametrize("strategy", ms.STRATEGIES)
def test_chains_divide_as_the_strategy_does(spark, strategy):
    run = engine.bfs(graph(spark, HUB), [0], strategy, options=Options(4, mdt=100, switch_below=1, record=True))
    for step, deg in ((2, [997]), (3, [1] * 200)):
        launch, worker, counts = chain.divided(strategy, np.array(deg), 4, 100, 1)
        want = {(r.launch, r.worker): r.load for r in run.worker_loads.where(f"superstep = {step}").groupBy("launch", "worker").agg(F.sum("load").alias("load")).collect()}
        assert Counter(zip(launch.tolist(), (worker + 1).tolist())) == want and counts.get("launches", 1) == run.rows[step - 1]["launches"]


def test_chains_begin_early_where_a_search_is_slow():
    assert chain.begins(4, 20, 40, 4_795_618) and chain.begins(20, 1 << 16, 10**6, 10**6)
    assert not chain.begins(3, 20, 40, 4_795_618) and not chain.begins(4, 20, 40, 7_820) and not chain.begins(30, (1 << 16) + 1, 10**6, 10**6)


@pytest.mark.parametrize("strategy", ms.STRATEGIES)
@pytest.mark.parametrize("small", (True, False))
def test_chains_go_on_over_larger_frontiers(monkeypatch, strategy, small):
    monkeypatch.setattr(chain, "FRONT_EDGES", 40)
    cells = [(i, j) for i in range(20) for j in range(20)]
    one = [(i * 20 + j, k, 1 + (7 * i + 3 * j * j) % 11) for i, j in cells for k in ((i * 20 + j + 1,) if j < 19 else ()) + ((i * 20 + j + 20,) if i < 19 else ())]
    edges = one + [(b, a, w) for a, b, w in one]
    deg = Counter(a for a, _, _ in edges)
    rows = [{"is_edge": True, "a": a, "b": b, "w": w, "v": 0, "has": False, "step": 0} for a, b, w in edges]
    rows += [{"is_edge": False, "a": a, "b": 0, "w": deg[a], "v": 0, "has": a == 0, "step": 0 if a == 0 else -1} for a in reversed(range(400))]
    given = [pa.RecordBatch.from_pylist(rows[i : i + 300]) for i in range(0, len(rows), 300)]
    out = pa.Table.from_batches(chain._runner("sssp", True, strategy, 4, 3, 2, 0, None, small)(given)).to_pylist()
    steps = [r for r in out if r["superstep"] is not None]
    assert max(r["active_edges"] for r in steps) > 40 and [r["superstep"] for r in steps] == list(range(1, len(steps) + 1))
    assert {0: 0} | {r["node"]: r["value"] for r in out if r["superstep"] is None} == shortest(edges, 0)


def test_candidates_combine_beyond_packed_integers():
    key, cand = np.array([3, 1, 3, 1]), np.array([1 << 62, 5, -(1 << 61), 7])
    for least, want in ((True, [5, -(1 << 61)]), (False, [7, 1 << 62])):
        at, best = chain._combined(key, cand, least)
        assert at.tolist() == [1, 3] and best.tolist() == want


def test_single_entries_are_not_broadcast(spark):
    own = graph(spark, HUB).cached()
    front = Front(spark.createDataFrame([(1, 0, 997)], "node long, value long, deg long"), 1, 997)
    rows = PLANS["EP"](front, own, programs.SSSP, Options(4, chunked=False)).rows
    plan = rows._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Broadcast" not in plan
    assert rows.count() == 997
    own.release()


def test_large_states_are_kept_as_improvements(spark, monkeypatch):
    edges = [(i, i + 1, 1) for i in range(30)] + [(0, 100 + i, 1) for i in range(50)]
    monkeypatch.setattr(engine, "SMALL_NODES", 0)
    monkeypatch.setattr(engine, "DELTAS", 3)
    want = shortest(edges, 0)
    assert {r.node: r.value for r in engine.sssp(graph(spark, edges), [0], "WD").state.collect()} == want
    monkeypatch.setattr(engine, "LOOKUP_ROWS", 60)
    monkeypatch.setattr(engine, "LOOKUP_SHARE", 1)
    assert {r.node: r.value for r in engine.sssp(graph(spark, edges), [0], "BS").state.collect()} == want


def test_targets_resumption_and_all_nodes(spark):
    edges = [(i, i + 1, 1) for i in range(12)] + [(0, 3, 9)]
    run = engine.sssp(graph(spark, edges), [0], "WD", target=3)
    assert {r.node: r.value for r in run.state.collect()}[3] == 3 and run.supersteps < 8
    every = engine.sssp(graph(spark, edges), [0], "WD", data_driven=False)
    assert {r.node: r.value for r in every.state.collect()} == shortest(edges, 0)
    old = engine.sssp(graph(spark, edges), [0], "WD").state
    more = [*edges, (0, 9, 2)]
    again = engine.traverse(graph(spark, more), programs.SSSP, spark.createDataFrame([(9, 2)], "node long, value long"), "WD", resume=old.select("node", "value"))
    assert {r.node: r.value for r in again.state.collect()} == shortest(more, 0) and again.supersteps == 4


def test_gathers(spark):
    g = graph(spark, [(1, 9, 2), (5, 9, 3), (9, 9, 1), (2, 3, 1)])
    values = g.nodes().select("node", F.col("node").cast("double").alias("value"))
    assert {r.node: r.value for r in engine.gather(g, programs.NEIGHBOUR_MEDIAN, values).collect()} == {1: 1.0, 5: 5.0, 9: 5.0, 2: 2.0, 3: 2.0}
    sums = engine.gather(g, programs.WEIGHTED_SUM, g.nodes().select("node", F.col("node").alias("value")), "WD")
    assert {r.node: r.value for r in sums.collect()}[9] == 2 + 15 + 9
    with pytest.raises(ValueError, match="not distributive"):
        engine.gather(g, programs.NEIGHBOUR_MEDIAN, values, "WD")


def test_capacity():
    words = 4 * 2**30 // 4
    assert 500e6 < words // 2 < 540e6 and 350e6 < words // 3 < 360e6  # edges of a list without and with weights in 4 GiB
    assert words // 1.5 >= 350e6  # rows of half as many nodes as edges


def test_rejections(spark):
    with pytest.raises(ValueError, match="no node"):
        engine.bfs(graph(spark, [(0, 1, 1)]), [9])
    with pytest.raises(ValueError, match="not distributive"):
        engine.traverse(graph(spark, [(0, 1, 1)]), programs.NEIGHBOUR_MEDIAN, None, "EP")
    for bad in ((0, None, 1), (0, 1, -1)):
        with pytest.raises(Exception, match="null end or a weight"):
            graph(spark, [bad]).edges.collect()


def test_split_invariants(spark):
    g = graph(spark, [(1, d, 1) for d in range(23)] + [(2, 3, 1)])
    parts = split_edges(g, 5).groupBy("parent", "child_no").count().collect()
    sizes = sorted(r["count"] for r in parts if r.parent == 1)
    assert sum(sizes) == 23 and len(sizes) == 5 and sizes[-1] <= 5 and sizes[-1] - sizes[0] <= 1


def test_blocks_are_even(spark):
    deg = spark.createDataFrame([(i, i % 7) for i in range(50)], "node long, deg long")
    loads = sorted(r["sum(len)"] for r in blocks(deg, 8).groupBy("worker").sum("len").collect())
    total = sum(i % 7 for i in range(50))
    assert sum(loads) == total and loads[-1] == -(-total // 8)


def test_scan_has_no_global_window(spark):
    frame = spark.range(1000).select(F.col("id").alias("node"), (F.col("id") % 5).alias("deg"))
    out = scan.inclusive(frame, ["node"], "deg")
    assert out.agg(F.max("hi")).first()[0] == 2000
    assert [r.rank for r in out.orderBy("node").limit(3).collect()] == [0, 1, 2]


def test_pages_round_trip_with_hub(spark):
    g = Graph.of(spark.range(500).select(F.lit(7).alias("src"), F.col("id").alias("dst"), F.lit(1).alias("w")), page=32)
    assert to_edges(g.pages()).exceptAll(g.edges).isEmpty() and g.pages().count() > 10


def test_threshold(spark):
    rmat = spark.createDataFrame([(i, 3) for i in range(90)] + [(99, 1181)], "node long, deg long")
    assert ms.find_mdt(rmat) == 118
    even = spark.createDataFrame([(i, 3) for i in range(90)] + [(99, 10)], "node long, deg long")
    assert ms.find_mdt(even) == 3


def test_advisor():
    base = dict(n=100, e=1000, max_deg=400, children=3, workers=8)
    words = ms.memory_words(100, 1000, 3, 8)
    assert ms.advise(base, 10**9)[0] == "EP"
    assert ms.advise(base, words["EP"] - 1)[0] == "WD"
    assert ms.advise(base | {"max_deg": 12}, words["EP"] - 1, diameter="large")[0] == "NS"
    assert ms.advise(base, words["EP"] - 1, distributive=False)[0] == "BS"
    assert words["EP"] > words["WD"] > words["BS"]
