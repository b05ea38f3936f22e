"""Recall of the graph search against brute force."""

import numpy as np

from partgraph.llm import neighbours as N


def test_recall_and_exact_scores(spark, tmp_path):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(900, 16)) * rng.uniform(0.5, 1.5, (900, 1))
    rows = [(i, [float(v) for v in r], 0) for i, r in enumerate(x)] + [(2000, None, 0), (2020, [0.0] * 16, 0), (2040, [float("nan")] * 16, 0)]
    spark.createDataFrame(rows, "vec_id long, embedding array<double>, rank int").write.parquet(str(tmp_path / "embeddings.parquet"))
    got = N.op9_nn_descent(spark, str(tmp_path)).collect()
    assert len(got) == 45 * 20
    hit = 0
    for r in got:
        s = x @ x[r.query_id]
        assert abs(r.score - s[r.vec_id]) < 1e-9
        s[r.query_id] = -np.inf
        hit += r.vec_id in set(np.argsort(-s)[:20].tolist())
    assert hit / len(got) >= 0.9


def test_small_table(spark, tmp_path):
    spark.createDataFrame([(0, [1.0, 0.0]), (1, [1.0, 1.0]), (2, [2.0, 0.0])], "vec_id long, embedding array<double>").write.parquet(str(tmp_path / "embeddings.parquet"))
    got = N.op9_nn_descent(spark, str(tmp_path)).orderBy("rank").collect()
    assert [(r.query_id, r.vec_id, r.score) for r in got] == [(0, 2, 2.0), (0, 1, 1.0)]


def recall(spark, path, x):
    spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vec_id long, embedding array<double>").write.parquet(f"{path}/embeddings.parquet")
    got = N.op9_nn_descent(spark, path).collect()
    assert len(got) == (len(x) + 19) // 20 * 20
    best = {}
    for q in range(0, len(x), 20):
        s = x @ x[q]
        s[q] = -np.inf
        best[q] = set(np.argsort(-s)[:20].tolist())
    hit = sum(r.vec_id in best[r.query_id] for r in got) / len(got)
    print("recall", hit)
    return hit


def test_graph_with_one_long_vector(spark):
    x = np.random.default_rng(3).normal(size=(600, 16))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    x[7] *= 50
    table = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vec_id long, embedding array<double>")
    graph = N.neighbour_graph(N._levelled(N.sound_vectors(table))).collect()
    length = (x * x).sum(1)
    last = np.sqrt(length.max() - length)
    s = x @ x.T + np.outer(last, last)
    np.fill_diagonal(s, -np.inf)
    best = np.argsort(-s, axis=1)[:, :10]
    got = {(r.u, r.v) for r in graph}
    hit = np.mean([(i, int(j)) in got for i in range(600) for j in best[i]])
    print("graph recall", hit)
    assert hit >= 0.9


def test_rounds_go_on_until_the_graph_settles(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(N, "BLOCK", 25)
    assert recall(spark, str(tmp_path), np.random.default_rng(4).normal(size=(3000, 64))) >= 0.9
