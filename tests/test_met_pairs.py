"""Pairs of suppliers that share an order, formed in buckets: against a loop over all pairs of rows."""

import random
from collections import Counter

import numpy as np
import pytest

from partgraph.operators.kernels import pairs_within
from partgraph.sources import graphs as G


@pytest.mark.parametrize(("rows", "pairs"), [(2_000_000, 1 << 21), (40, 30)])
def test_buckets_equal_a_loop(spark, monkeypatch, rows, pairs):
    monkeypatch.setattr(G, "MET_ROWS", rows)
    monkeypatch.setattr(G, "MET_PAIRS", pairs)
    rnd = random.Random(4)
    ids = [None, -(10**15), -1, *(k * 10**14 for k in range(25))]
    lines = [(rnd.choice([None, -(10**17), *range(60)]), rnd.choice(ids)) for _ in range(400)]
    lines += [(7, x) for x in ids for _ in range(2)]  # a large group with repeats
    want = Counter((x, y) for g, x in lines for h, y in lines if None not in (g, x, y) and g == h and x < y)
    got = G.met_pairs(spark.createDataFrame(lines, "l_orderkey long, l_suppkey long")).collect()
    assert len(got) == len(want) and {(r.src, r.dst): r.n for r in got} == want
    assert G.met_pairs(spark.createDataFrame([], "l_orderkey long, l_suppkey long")).count() == 0


def test_no_pair_is_a_row_of_a_shuffle(spark, sf):
    """The lines of an order once met in a join, each pair of them a row that was shuffled to be counted."""
    plan = G.cosupp(spark, sf).edges._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "Aggregate" not in plan and "blob" in plan


def test_pairs_come_in_parts():
    """One group of 300 members in parts of some 1,000 pairs: none is lost or given twice."""
    member = np.arange(300) * 10**12
    parts = list(pairs_within(np.zeros(300, np.int64), member, 1000))
    assert max(len(src) for src, _, _ in parts) <= 1000
    assert len({(a, b) for src, dst, _ in parts for a, b in zip(src.tolist(), dst.tolist(), strict=True)}) == sum(len(src) for src, _, _ in parts) == 300 * 299 // 2
    assert all((src < dst).all() and (n == 1).all() for src, dst, n in parts)
