"""The closing test in cells against plain loops, for every number of colours."""

import itertools
import random
from collections import Counter

import pytest

from partgraph.operators import triangles as T
from partgraph.operators.kernels import unpacked_edges
from partgraph.sources.graphs import PartitionedGraph


def _plain(edges, sg):
    out = set()
    for a, b, c in itertools.combinations(sorted(sg), 3):
        if {(a, b), (b, c), (a, c)} <= edges:
            p, q, r = sg[a], sg[b], sg[c]
            kind = "i" if p == q == r else "first" if q == r else "middle" if p == r else "last" if p == q else "iii"
            out.add((a, b, c, kind, -1 if kind == "iii" else q if kind == "first" else p))
    return out


@pytest.fixture(scope="module")
def graph(spark):
    rnd = random.Random(2)
    sg = {v * 10**12 - 5: rnd.randrange(4) for v in range(24)}
    edges = {e for e in itertools.combinations(sorted(sg), 2) if rnd.random() < 0.4}
    v = spark.createDataFrame(list(sg.items()), "vid long, sg long")
    return PartitionedGraph(v, spark.createDataFrame([(*e, 1) for e in edges], "src long, dst long, weight long")), _plain(edges, sg)


@pytest.mark.parametrize(("colours", "by"), [(1, "id"), (2, "degree"), (4, "id"), (None, "degree")])
def test_cells_equal_plain_loops(graph, colours, by):
    g, want = graph
    got = [tuple(r) for r in T.in_cells(g.owned_edges(), False, by, colours).collect()]
    assert len(got) == len(set(got)) and set(got) == want
    counts = {(r.kind, r.own): r.triangles for r in T.in_cells(g.owned_edges(), True, by, colours).collect()}
    assert counts == Counter(x[3:] for x in want)


@pytest.mark.parametrize("count", [T.count_types, T.count_kernel, T.type2_placement, T.count_vertex_centric, T.transitivity])
def test_no_path_is_shuffled(graph, count):
    plan = count(graph[0])._jdf.queryExecution().optimizedPlan().toString()
    # the closing test was a semi join of two-step paths, the forward form exploded lists of common neighbours
    assert "LeftSemi" not in plan and "array_intersect" not in plan


def test_edges_travel_packed(spark):
    """Cells of 40,000 edges once got a row of six columns for each edge and colour; a few bytes an edge must do."""
    rnd = random.Random(5)
    edges = sorted({tuple(sorted(rnd.sample(range(3000), 2))) for _ in range(40_000)})
    df = spark.createDataFrame(edges, "src long, dst long")
    blobs = T._packed(df.coalesce(1), 3).collect()
    assert sum(len(r.blob) for r in blobs) < 4 * len(edges)
    back = set()
    for r in blobs:
        ids, s, d = unpacked_edges(r.blob)
        back |= set(zip(ids[s].tolist(), ids[d].tolist(), strict=True))
    assert back == set(edges)


def test_owner_null_and_unknown_ends(spark):
    """Ids far apart, an owner null (equal to no other) and an edge to a vertex without owner, which plays no part."""
    sg = {-(10**15): None, 3: 1, 10**17: 1, 10**18: None, 5: 2}
    edges = [*itertools.combinations(sorted(sg), 2), (3, 4), (4, 5)]
    v = spark.createDataFrame(list(sg.items()), "vid long, sg long")
    found = T.in_cells(spark.createDataFrame(edges, "src long, dst long"), False, vertices=v).collect()
    kinds = {(r.a, r.b, r.c): (r.kind, r.own) for r in found}
    assert set(kinds) == set(itertools.combinations(sorted(sg), 3))
    with_two = {t: k for t, k in kinds.items() if {3, 10**17} <= set(t)}
    assert set(with_two.values()) == {("first", 1), ("middle", 1), ("last", 1)} and len(with_two) == 3
    assert all(k == ("iii", -1) for t, k in kinds.items() if t not in with_two)


def test_large_and_small_subgraphs_together(graph):
    g, want = graph
    for cap in (10**6, 95, 0):
        assert {r.tri_type: r.triangles for r in T.count_kernel(g, cap).collect()} == Counter(k if k in ("i", "iii") else "ii" for *_, k, _ in want)
        assert {(r.a, r.b, r.c) for r in T.triangles_kernel(g, cap).collect()} == {x[:3] for x in want}
