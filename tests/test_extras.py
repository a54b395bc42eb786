"""Spanning forests, betweenness and table functions against plain searches."""

import math
import random
from collections import deque

import numpy as np

from skewgraph import queries as q
from skewgraph.graph import Graph
from skewgraph.operators import extras
from skewgraph.views import VIEWS, embedding_knn

SF = "/root/testdata/sf0.001"


def kruskal(edges):
    root = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    out = []
    for w, a, b in sorted((w, min(s, d), max(s, d)) for s, d, w in edges if s != d):
        if find(a) != find(b):
            root[find(a)] = find(b)
            out.append((w, a, b))
    return sorted(out)


def dependency(edges, start):
    out, level, paths, order = {}, {start: 0}, {start: 1}, []
    for s, d, _ in edges:
        out.setdefault(s, []).append(d)
    line = deque([start])
    while line:
        v = line.popleft()
        order.append(v)
        for u in out.get(v, []):
            if u not in level:
                level[u], paths[u] = level[v] + 1, 0
                line.append(u)
            if level[u] == level[v] + 1:
                paths[u] += paths[v]
    score = dict.fromkeys(order, 0.0)
    for v in reversed(order):
        score[v] = sum(paths[v] / paths[u] * (1 + score[u]) for u in out.get(v, []) if level[u] == level[v] + 1)
    return score | {start: 0.0}


def test_spanning_forest(spark):
    rng = random.Random(5)
    edges = [(1, 1, 0), (1, 2, 9), (2, 1, 3)] + [(rng.randrange(60), rng.randrange(60), rng.randrange(1, 6)) for _ in range(90)]
    found = extras.spanning_forest(spark.createDataFrame(edges, "src long, dst long, w long"))
    assert sorted(tuple(r) for r in found.select("w", "lo", "hi").collect()) == kruskal(edges)
    assert extras.spanning_forest(spark.createDataFrame([], "src long, dst long, w long")).count() == 0


def test_spanning_forest_of_a_larger_graph(spark):
    edges = [tuple(r) for r in VIEWS["part_next"](spark, SF).collect()]
    assert sorted(tuple(r) for r in q.forest("part_next")(spark, SF).select("w", "lo", "hi").collect()) == kruskal(edges)


def test_betweenness(spark):
    rng = random.Random(6)
    edges = sorted({(rng.randrange(30), rng.randrange(30)) for _ in range(70)})
    edges = [(0, 1, 1), *((a, b, 1) for a, b in edges if a != b and (a, b) != (0, 1))]
    g = Graph.from_rows(spark, edges)
    nodes = {v for e in edges for v in e[:2]}
    want = dependency(edges, 0)
    assert {r["node"]: r["score"] for r in extras.dependencies(g, 0).collect()} == {v: round(want.get(v, 0.0), 6) for v in nodes}
    total = dict.fromkeys(nodes, 0.0)
    for v in nodes:
        for u, x in dependency(edges, v).items():
            total[u] += x
    for most in (10**6, 200):  # one block of sources, several
        found = {r["node"]: r["score"] for r in extras.betweenness(g, most_rows=most).collect()}
        assert found.keys() == total.keys() and all(abs(found[v] - total[v]) < 2e-6 for v in nodes)


def test_sources_that_reach_little_are_swept_at_once(spark, monkeypatch):
    g, sweeps = Graph.from_rows(spark, [(10 * i + j, 10 * i + j + 1) for i in range(40) for j in range(3)]), []
    own = extras._swept
    monkeypatch.setattr(extras, "_swept", lambda *a: sweeps.append(1) or own(*a))
    found = {r["node"]: r["score"] for r in extras.betweenness(g, most_rows=1000).collect()}
    assert found == {10 * i + j: (0.0, 2.0, 2.0, 0.0)[j] for i in range(40) for j in range(4)} and len(sweeps) == 1


def test_nearest_vectors(spark, tmp_path):
    rng = np.random.default_rng(3)
    v = np.concatenate([rng.normal(size=(60, 8)), np.tile(rng.normal(size=(1, 8)), (20, 1))])
    rows = [(i, x.tolist()) for i, x in enumerate(v)] + [(900, None), (901, [0.0] * 8)]
    spark.createDataFrame(rows, "vec_id long, embedding array<double>").write.parquet(f"{tmp_path}/embeddings.parquet")
    cosine = lambda i, j: sum(a * b for a, b in zip(v[i].tolist(), v[j].tolist())) / (math.sqrt(sum(a * a for a in v[i].tolist())) * math.sqrt(sum(a * a for a in v[j].tolist())))
    want = {(i, j, n + 2) for i in range(80) for n, j in enumerate(sorted((j for j in range(80) if j != i), key=lambda j: (-cosine(i, j), j))[:8])}
    assert {tuple(r) for r in embedding_knn(spark, str(tmp_path), block=16).collect()} == want


def test_generators_and_checks_read_tables(spark):
    made = q.queries()
    for name, given in (("gen_rmat", "orders"), ("gen_er", "orders"), ("gen_lattice", "events"), ("distributive_check", "lineitem")):
        assert any(f"/{given}.parquet" in f for f in made[name](spark, SF).inputFiles())
    assert {r.program: r.violations > 0 for r in q.distributive_check(spark, SF).collect()} == {"min_plus": False, "max_min": False, "mean": True}


def test_table_functions(spark):
    assert sorted(map(tuple, q.udtf_frontier_blocks(spark, SF).collect())) == sorted(map(tuple, q.wd_blocks_example(spark, SF).collect()))
    assert sorted(map(tuple, q.udtf_split_node(spark, SF).collect())) == sorted(map(tuple, q.ns_split("part_next")(spark, SF).collect()))
