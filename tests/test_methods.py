"""Partitions, kernels, further triangle, cluster and forest methods, and traversals against plain Python."""

import heapq
import itertools
import random
from collections import Counter, deque

import pytest
from test_graph import made, random_graph, rows  # noqa: F401  the fixture

from partgraph.operators import clustering as K
from partgraph.operators import forest as M
from partgraph.operators import partitions as P
from partgraph.operators import traversal as V
from partgraph.operators import triangles as T
from partgraph.operators.bsp import MessageLog, Phase, all_vote, run_bsp, send


def near(edges):
    adj = {}
    for a, b in edges:
        adj.setdefault(a, set()).add(b)
        adj.setdefault(b, set()).add(a)
    return adj


def hops(adj, source):
    dist, queue = {source: 0}, deque([source])
    while queue:
        x = queue.popleft()
        for y in adj.get(x, ()):
            if y not in dist:
                dist[y] = dist[x] + 1
                queue.append(y)
    return dist


def test_kernels_and_other_triangle_forms(spark, random_graph):  # noqa: F811
    owner, edges = random_graph
    g = made(spark, owner, edges)
    want = rows(T.triangles(g))
    kinds = Counter(r.tri_type for r in T.triangles(g).collect())
    assert rows(T.triangles_kernel(g)) == want
    assert rows(T.triangles_kernel(g, cap=30)) == want  # some subgraphs are too large for the kernel
    assert {r.tri_type: r.triangles for r in T.count_kernel(g).collect()} == kinds
    assert rows(T.triangles_colour(g, 3)) == want
    assert rows(T.triangles_bsp(g, prune=True)[0]) == want
    per_edge = {(r.src, r.dst): r.triangles for r in T.per_edge(T.triangles(g)).collect()}
    assert sum(per_edge.values()) == 3 * len(want)
    assert sum(r.triangles for r in T.per_vertex(T.triangles(g)).collect()) == 3 * len(want)
    t = T.transitivity(g).first()
    deg = Counter(x for e in edges for x in e)
    wedges = sum(d * (d - 1) // 2 for d in deg.values())
    assert (t.triangles, t.wedges, t.transitivity) == (len(want), wedges, 3_000_000 * len(want) // wedges)
    r = T.triangle_recall(g).first()
    assert r.found + r.missed == r.total == len(want)
    assert T.triangles_estimate(g, 100).first().estimate == len(want)


def test_truss(spark, random_graph):  # noqa: F811
    owner, edges = random_graph
    left = set(edges)
    while True:
        adj = near(left)
        bad = {(a, b) for a, b in left if len(adj[a] & adj[b]) < 2}
        if not bad:
            break
        left -= bad
    assert left and sorted(map(tuple, T.k_truss(made(spark, owner, edges), 4).collect())) == sorted(left)


def test_extreme_partitions(spark, random_graph):  # noqa: F811
    owner, edges = random_graph
    g = made(spark, owner, edges)
    one, log = T.triangles_bsp(P.partition_single(g))
    assert len(log) == 1 and rows(one) == rows(T.triangles(g))
    single = T.triangles(P.partition_singletons(g)).select("tri_type").distinct().collect()
    assert [r.tri_type for r in single] == ["iii"]
    _, log = T.triangles_bsp(P.partition_range(g, 2))
    assert len(log) == 2 and log[1]["messages"] == 0
    assert P.graph_shape(P.partition_components(g)).first().cut == 0
    sub = P.assign_subgraphs(g)
    adj = near(edges)
    inside = near([e for e in edges if owner[e[0]] == owner[e[1]]])
    for r in sub.vertices.collect():
        assert r.sg == min(hops(inside, r.vid))
    assert adj


def test_label_propagation_respects_the_cap_and_cuts_less(spark):
    edges = {}
    for c in range(4):
        members = list(range(c, 40, 4))  # communities that id ranges cut apart
        for a, b in itertools.combinations(members, 2):
            edges[a, b] = 1
    for c in range(3):
        edges[c, c + 1] = 1
    g = made(spark, {i: 0 for i in range(40)}, edges)
    before, after = P.graph_shape(P.partition_range(g, 4)).first(), P.graph_shape(P.partition_lp(g, 4, rounds=10, slack=0.3)).first()
    assert after.cut < before.cut and after.l_max <= 14 and after.n == 40


def test_meta_graph(spark, random_graph):  # noqa: F811
    owner, edges = random_graph
    g = made(spark, owner, edges)
    want = Counter(tuple(sorted((owner[a], owner[b]))) for a, b in edges if owner[a] != owner[b])
    assert {(r.src_sg, r.dst_sg): r.cut_edges for r in P.meta_graph(g).collect()} == want
    adj = near(want)
    m = P.meta_diameter(g).first()
    assert m.meta_diameter == max(max(hops(adj, s).values()) for s in adj) and m.subgraphs == len(set(owner.values()))
    assert sorted((r.src, r.dst, r.weight) for r in V.coarsen(g).edges.collect()) == sorted((a, b, min(w for e, w in edges.items() if tuple(sorted((owner[e[0]], owner[e[1]]))) == (a, b))) for a, b in want)


def test_boundary_crossed_many_times(spark):
    """Two subgraphs side by side, a path that goes to and fro: more exchanges than the meta-graph's diameter."""
    edges = {(i, i + 1): 1 for i in range(8)}
    g = made(spark, {i: i % 2 for i in range(9)}, edges)
    start = spark.createDataFrame([(0, 0)], "centre_rank int, vid long")
    labels, steps = K.assign(g, start, "subgraph")
    assert {r.vid: r.dist for r in labels.collect()} == {i: i for i in range(9)}
    assert steps > P.meta_diameter(g).first().meta_diameter == 1


def test_ties_unreached_and_checks(spark):
    g = made(spark, {1: 0, 2: 0, 3: 1, 4: 1, 5: 1}, {(1, 2): 1, (2, 3): 1, (4, 5): 1})
    centres = spark.createDataFrame([(0, 3), (1, 1)], "centre_rank int, vid long")
    for unit in ("vertex", "subgraph"):
        labels = K.assign(g, centres, unit)[0]
        assert sorted(map(tuple, labels.select("vid", "dist", "centre_rank").collect())) == [(1, 0, 1), (2, 1, 0), (3, 0, 0)]
    assert {r.centre_rank: (r.vertices, r.pieces) for r in K.check_clusters(g, labels).collect()} == {0: (2, 1), 1: (1, 1)}
    assert {r.centre_rank: (r.vertices, r.radius, r.inner_edges, r.cut_edges) for r in K.cluster_summary(g, labels).collect()} == {0: (2, 1, 1, 1), 1: (1, 0, 0, 1)}


def test_threshold_equal_to_the_cut(spark):
    g = made(spark, {1: 0, 2: 0, 3: 1, 4: 1}, {(1, 2): 1, (2, 3): 1, (3, 4): 1})
    _, info = K.kway_cluster(g, 2, 3, max_rounds=1)
    assert K.kway_cluster(g, 2, info["cut"], max_rounds=1)[1]["accepted"]
    assert not K.kway_cluster(g, 2, info["cut"], max_rounds=1, strict=True)[1]["accepted"]


def test_draws(spark):
    owner = {i: 0 if i < 2 else 1 for i in range(100)}
    g = made(spark, owner, {(0, 1): 1})
    small = {"reservoir": 0, "per_subgraph": 0}
    for kind in small:
        for r in range(12):
            small[kind] += sum(x.vid < 2 for x in K.draw_centres(g, 2, round_=r, sampling=kind).collect())
    assert small["per_subgraph"] > small["reservoir"]
    got = K.draw_exchange(g, 3).collect()
    want = {(r.centre_rank, r.vid) for r in K.draw_centres(g, 3).collect()}
    assert {s: {(r.centre_rank, r.vid) for r in got if r.to_sg == s} for s in (0, 1)} == {0: want, 1: want} and got[0].received == 5


def test_weighted_labels(spark, random_graph):  # noqa: F811
    owner, edges = random_graph
    g = made(spark, owner, edges)
    centres = K.draw_centres(g, 3)
    best = {}
    queue = [(0, r.centre_rank, r.vid) for r in centres.collect()]
    heapq.heapify(queue)
    while queue:
        d, r, x = heapq.heappop(queue)
        if x in best:
            continue
        best[x] = (d, r)
        for (a, b), w in edges.items():
            for p, q in ((a, b), (b, a)):
                if p == x and q not in best:
                    heapq.heappush(queue, (d + w, r, q))
    assert {r.vid: (r.dist, r.centre_rank) for r in K.assign_weighted(g, centres).collect()} == best


@pytest.mark.parametrize("unit", ["single", "filter"])
def test_other_forests(spark, random_graph, unit):  # noqa: F811
    owner, edges = random_graph
    g = made(spark, owner, edges)
    want = sorted(map(tuple, M.spanning_forest(g, "vertex")[0].select("src", "dst", "weight").collect()))
    chosen, tree, _ = M.spanning_forest(g, unit)
    assert sorted(map(tuple, chosen.select("src", "dst", "weight").collect())) == want
    quick, _, _ = M.spanning_forest(g, "subgraph", finish=1000)
    assert sorted(map(tuple, quick.select("src", "dst", "weight").collect())) == want
    inside = M.local_forest(g).where("is_edge").select("src", "dst", "weight").collect()
    assert set(map(tuple, inside)) <= set(want) and all(owner[r.src] == owner[r.dst] for r in inside)
    s = M.forest_summary(g, chosen).first()
    assert (s.edges, s.weight, s.trees) == (len(want), sum(w for *_, w in want), len({r.root for r in tree.collect()}))
    assert M.single_linkage(g, chosen, 2).select("cluster").distinct().count() == s.trees + 2


def test_literal_halt_stops_early(spark):
    g = made(spark, {1: 0, 3: 0, 2: 1, 4: 1}, {(1, 2): 1, (3, 4): 2, (2, 4): 5})
    assert M.forest_summary(g, M.spanning_forest(g)[0]).first().trees == 1
    assert M.forest_summary(g, M.spanning_forest(g, literal_halt=True)[0]).first().trees == 2


def test_equal_weights(spark):
    g = made(spark, {i: i for i in range(1, 5)}, {(1, 2): 1, (2, 3): 1, (3, 4): 1, (1, 4): 1})
    for unit in ("vertex", "subgraph", "single"):
        assert sorted((r.src, r.dst) for r in M.spanning_forest(g, unit)[0].collect()) == [(1, 2), (1, 4), (2, 3)]


def test_traversals(spark, random_graph):  # noqa: F811
    owner, edges = random_graph
    g = made(spark, owner, edges)
    adj = near(edges)
    assert {r.vid: r.dist for r in V.sssp(g, 3).collect()} == hops(adj, 3) == {r.vid: r.dist for r in V.sssp(g, 3, "subgraph").collect()}
    assert {r.vid for r in V.reachable(g, [3]).collect() if r.reached} == set(hops(adj, 3))
    score = dict.fromkeys(owner, 0.0)
    for s in (0, 5):
        dist = hops(adj, s)
        paths = {s: 1.0}
        for x in sorted(dist, key=dist.get)[1:]:
            paths[x] = sum(paths[y] for y in adj[x] if dist[y] == dist[x] - 1)
        owed = dict.fromkeys(dist, 0.0)
        for x in sorted(dist, key=dist.get, reverse=True):
            for y in adj.get(x, ()):
                if dist[y] == dist[x] - 1:
                    owed[y] += paths[y] / paths[x] * (1 + owed[x])
            if x != s:
                score[x] += owed[x]
    got = {r.vid: r.score for r in V.betweenness(g, [0, 5]).collect()}
    assert all(abs(got.get(v, 0) - x) < 1e-5 for v, x in score.items())
    ranks = V.pagerank(g, 20).collect()
    assert sum(r.score for r in ranks) <= V.UNIT


def test_superstep_helpers(spark):
    g = made(spark, {1: 0, 2: 1}, {(1, 2): 1})
    log = MessageLog()
    sent = send(g.owned_edges(), log, Phase.EXCHANGE)
    assert log.steps == [(0, "exchange", 1, 0, 1)] and sent.count() == 1 and log.table(spark).count() == 1
    assert all_vote(g.vertices.limit(0), g.vertices) and not all_vote(g.vertices.where("sg = 0"), g.vertices)
    assert run_bsp(3, lambda k, s: (s - 1, s == 1)) == 0
    with pytest.raises(RuntimeError):
        run_bsp(0, lambda k, s: (s, False), 3)


def test_empty_graph(spark):
    g = made(spark, {1: 0}, {(1, 2): 1})
    g = type(g)(g.vertices, g.edges.limit(0))
    assert T.triangles_kernel(g).count() == 0 and T.count_kernel(g).count() == 0 and T.triangles_bsp(g)[1][0]["messages"] == 0
    assert M.spanning_forest(g)[0].count() == 0 and M.spanning_forest(g)[1].count() == 1
    assert K.assign(g, K.draw_centres(g, 3), "subgraph")[0].count() == 1
