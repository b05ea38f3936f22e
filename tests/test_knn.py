"""Nearest neighbours in blocks against plain loops, ties included."""

import math
import random

from partgraph.sources import graphs as G


def test_blocks_equal_plain_loops(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(G, "KNN_BLOCK", 7)
    rnd = random.Random(1)
    rows = [(i * 3, [float(rnd.randint(0, 2)) for _ in range(4)], i % 3) for i in range(40)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(str(tmp_path / "embeddings.parquet"))
    want = {}
    for i, x, _ in rows:
        near = sorted((math.sqrt(sum((a - b) ** 2 for a, b in zip(x, y, strict=True))), j) for j, y, _ in rows if j != i)[:5]
        want |= {(min(i, j), max(i, j)): round(d * 1e6) for d, j in near}
    g = G.emb_knn(spark, str(tmp_path), k=5)
    assert {(r.src, r.dst): r.weight for r in g.edges.collect()} == want
    # the edges are stored, not compared anew by each reader
    assert "Join" not in g.edges._jdf.queryExecution().optimizedPlan().toString()
    few = G.emb_knn(spark, str(tmp_path), k=100).edges
    assert few.count() == 40 * 39 // 2
