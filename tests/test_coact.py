"""Pairs of users that act alike, met in blocks: against a loop over all pairs of acts."""

import random
from collections import Counter

import pytest

from partgraph.sources import graphs as G


@pytest.mark.parametrize(("block", "pairs"), [(300_000, 1 << 21), (40, 30)])
def test_blocks_equal_a_loop(spark, monkeypatch, block, pairs):
    monkeypatch.setattr(G, "COACT_BLOCK", block)
    monkeypatch.setattr(G, "COACT_PAIRS", pairs)
    rnd = random.Random(3)
    acts = {(u * 10**15 - 7, t, w): rnd.randint(1, 5) for u in range(30) for t in ("click", "view", None) for w in (0, 3600, None) if rnd.random() < 0.5}
    acts[None, "click", 0] = 2
    want = Counter()
    for (u, t, w), n in acts.items():
        for (v, t2, w2), m in acts.items():
            if None not in (u, v, t, w) and (t, w) == (t2, w2) and u < v:
                want[u, v] += n * m
    rows = [(*k, n) for k, n in acts.items()]
    got = G.coact_pairs(spark.createDataFrame(rows, "user_id long, event_type string, w long, n long"))
    assert {(r.src, r.dst): r.n for r in got.collect()} == want
    # pairs of acts were shuffled to be summed
    assert "sum" not in got._jdf.queryExecution().optimizedPlan().toString()
    assert G.coact_pairs(spark.createDataFrame([], "user_id long, event_type string, w long, n long")).count() == 0
