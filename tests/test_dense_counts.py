"""Counts of dense graphs by rows of bits, against loops, products of matrices and two-step paths."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from partgraph.operators import kernels as K
from partgraph.operators import triangles as T


@pytest.mark.parametrize("paint", [[0, 1, 2], [0, 0, 1], [1, 2, 2], [2, 2, 2]])
def test_rows_of_bits_equal_loops(paint):
    rng = np.random.default_rng(3)
    n, owners = 90, 5
    colour, own = rng.choice(sorted(set(paint)), n), rng.integers(0, owners - 1, n)
    edges = [e for e in itertools.combinations(range(n), 2) if rng.random() < 0.5]
    want = np.zeros((owners,) * 3, np.int64)
    there = set(edges)
    for a, b in edges:
        for c in range(b + 1, n):
            if (a, c) in there and (b, c) in there and sorted(colour[[a, b, c]].tolist()) == paint:
                want[own[a], own[b], own[c]] += 1
    s, d = np.array(edges + edges[:50], np.int32).T
    assert (K.closing_counts(s, d, n, own, owners, colour, paint) == want).all() and want.any()
    assert not K.closing_counts(s[:0], d[:0], n, own, owners, colour, paint).any()


def test_dense_cells_form_no_paths(spark, monkeypatch):
    n, rule = 1200, "(a * a + 3 * b * b + a * b) % 10 < 6"
    ids = spark.range(n)
    edges = ids.toDF("a").crossJoin(ids.toDF("b")).where(f"a < b and {rule}").select(F.col("a").alias("src"), F.col("b").alias("dst"))
    vertices = ids.select(F.col("id").alias("vid"), F.expr("case when id <> 77 then id % 4 end").alias("sg"))
    rows = lambda df: {(r.kind, r.own): r.triangles for r in df.collect()}
    # weighted counts still go by paths
    want = rows(T.in_cells(edges, True, vertices=vertices.withColumn("weight", F.lit(1))))
    a, b = np.triu_indices(n, 1)
    m = np.zeros((n, n))
    m[a, b] = (a * a + 3 * b * b + a * b) % 10 < 6
    assert sum(want.values()) == int(((m @ m) * m).sum())
    # every path of these cells was formed before, some hundred for a word of bits
    monkeypatch.setattr(K, "closing_paths", None)
    assert rows(T.in_cells(edges, True, vertices=vertices)) == want
    assert sum(rows(T.in_cells(edges, True, "id", 4)).values()) == sum(want.values())
