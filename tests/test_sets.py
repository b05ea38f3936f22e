"""Transitivity of vertices that share an item, against all pairs and triples."""

import itertools
import random

import pytest

from partgraph.operators import triangles as T


@pytest.mark.parametrize("kinds", [1, 4, 40])
def test_sets_equal_plain_loops(spark, kinds):
    rnd = random.Random(kinds)
    pool = [set(rnd.sample("abcdefgh", rnd.randint(1, 2))) for _ in range(kinds)]
    has = {v: rnd.choice(pool) for v in range(40)}
    adjacent = lambda x, y: bool(has[x] & has[y])
    tri = sum(adjacent(a, b) and adjacent(b, c) and adjacent(a, c) for a, b, c in itertools.combinations(has, 3))
    degree = [sum(adjacent(x, y) for y in has if y != x) for x in has]
    wedges = sum(d * (d - 1) // 2 for d in degree)
    rows = [(v, i) for v, items in has.items() for i in items] * 2 + [(None, "a"), (99, None)]
    got = T.transitivity_of_sets(spark.createDataFrame(rows, "vid long, item string")).first()
    assert tuple(got) == (tri, wedges, 3_000_000 * tri // wedges)


def test_many_alike_form_no_pairs(spark):
    """20,000 vertices of one set: two hundred million pairs, and three million times the triangles is beyond a bigint."""
    n = 20_000
    got = T.transitivity_of_sets(spark.range(n).selectExpr("id vid", "'a' item")).first()
    assert tuple(got) == (n * (n - 1) * (n - 2) // 6, n * ((n - 1) * (n - 2) // 2), 1_000_000)
    assert tuple(T.transitivity_of_sets(spark.createDataFrame([], "vid long, item string")).first()) == (0, 0, None)
