"""Methods against plain Python on small graphs."""

import itertools
import random

import pytest

from partgraph.operators import clustering as K
from partgraph.operators import forest as M
from partgraph.operators import triangles as T
from partgraph.sources.graphs import PartitionedGraph


def made(spark, owner, edges):
    v = spark.createDataFrame([(i, s) for i, s in owner.items()], "vid long, sg long")
    e = spark.createDataFrame([(min(a, b), max(a, b), w) for (a, b), w in edges.items()], "src long, dst long, weight long")
    return PartitionedGraph(v, e)


@pytest.fixture(scope="module")
def random_graph():
    rnd = random.Random(4)
    owner = {i: rnd.randrange(4) for i in range(40)}
    edges = {(a, b): rnd.randint(1, 9) for a, b in itertools.combinations(range(36), 2) if rnd.random() < 0.2}
    return owner, edges


def rows(df):
    return sorted((r.a, r.b, r.c) for r in df.collect())


def test_triangles(spark, random_graph):
    owner, edges = random_graph
    g = made(spark, owner, edges)
    want = [t for t in itertools.combinations(range(36), 3) if all(p in edges for p in itertools.combinations(t, 2))]
    assert want
    found, log = T.triangles_bsp(g)
    first_away = [t for t in want if owner[t[1]] == owner[t[2]] != owner[t[0]]]
    for got in (T.triangles(g), found, T.triangles_bsp(g, "receive_check")[0], T.triangles_vertex_centric(g), T.triangles_node_iterator(g), T.triangles_forward(g)):
        assert rows(got) == want
    assert rows(T.triangles_bsp(g, "as_printed")[0]) == [t for t in want if t not in first_away] and first_away
    counts = {(r["form"], r["round"]): r.messages for r in T.message_counts(g).collect()}
    assert counts["subgraph", 1] == log[0]["messages"] and counts["subgraph", 2] == log[1]["messages"] < counts["vertex", 2]
    assert len(log) == 3


def test_two_supersteps_without_third_subgraph(spark):
    g = made(spark, {1: 0, 2: 1, 3: 1}, {(1, 2): 1, (1, 3): 1, (2, 3): 1})
    found, log = T.triangles_bsp(g)
    assert rows(found) == [(1, 2, 3)] and len(log) == 2
    assert rows(T.triangles_bsp(g, "as_printed")[0]) == []


@pytest.mark.parametrize("unit", ["vertex", "subgraph"])
def test_forest(spark, random_graph, unit):
    owner, edges = random_graph
    top = {i: i for i in owner}

    def find(x):
        while top[x] != x:
            x = top[x]
        return x

    want = []
    for w, a, b in sorted((w, a, b) for (a, b), w in edges.items()):
        x, y = find(a), find(b)
        if x != y:
            top[max(x, y)] = min(x, y)
            want.append((a, b, w))
    chosen, tree, _ = M.spanning_forest(made(spark, owner, edges), unit)
    assert sorted((r.src, r.dst, r.weight) for r in chosen.collect()) == sorted(want)
    assert {r.vid: r.root for r in tree.collect()} == {i: find(i) for i in owner}


def test_clusters(spark, random_graph):
    owner, edges = random_graph
    g = made(spark, owner, edges)
    centres = K.draw_centres(g, 3)
    a, slow = K.assign(g, centres, "vertex")
    b, fast = K.assign(g, centres, "subgraph")
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect())) and fast <= slow
    lab = {r.vid: r.centre_rank for r in a.collect()}
    cut = K.edge_cut(g, a).first()
    assert cut.local_cut + cut.remote_cut == sum(lab.get(x) != lab.get(y) for x, y in edges)
    _, info = K.kway_cluster(g, 3, len(edges))
    assert info["accepted"] and info["rounds"] == 1
    _, info = K.kway_cluster(g, 3, -1, max_rounds=2)
    assert not info["accepted"] and info["rounds"] == 2
