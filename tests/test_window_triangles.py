"""Triangles of each window, with user ids beyond 100,000."""

import itertools
import math

from partgraph.operators import triangles as T
from partgraph.streaming.events import window_triangles


def test_large_user_ids_stay_in_their_window(spark):
    users = [7, 150_000, 2_500_000, 9_000_000]
    rows = [(b, "click", u, 1) for b, n in ((3600, 3), (7200, 4), (10800, 2)) for u in users[:n]]
    found = spark.createDataFrame(rows, "bucket long, event_type string, user_id long, n long")
    assert {r.bucket: r.triangles for r in window_triangles(found).collect()} == {3600: 1, 7200: 4}


def test_no_pairs_of_alike_users(spark, monkeypatch):
    """Every pair of users of a window was once written; users that did the same things count together."""
    types = [("click",), ("view",), ("click", "view"), ("buy", "view"), (None,)]
    sets = {b: [types[u * 7 % len(types) if b else 0] for u in range(n)] for b, n in ((0, 1200), (3600, 60))}
    rows = [(b, t, u, 1) for b, users in sets.items() for u, done in enumerate(users) for t in done] + [(3600, "view", None, 1)]
    want = {0: math.comb(1200, 3), 3600: 0}
    meet = [{t for t in done if t} for done in sets[3600]]
    want[3600] = sum(bool(x & y and x & z and y & z) for x, y, z in itertools.combinations(meet, 3))
    written = []
    plain = T.spill
    monkeypatch.setattr(T, "spill", lambda df, *done: written.append(plain(df, *done)) or written[-1])
    found = spark.createDataFrame(rows, "bucket long, event_type string, user_id long, n long")
    assert {r.bucket: r.triangles for r in window_triangles(found).collect()} == want
    assert sum(t.count() for t in written if t._spilled) < 100
