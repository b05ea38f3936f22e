"""Listed triangles of pages that share addresses, against plain loops."""

import itertools
import random

import pytest

import __spark_entry__ as entry
from partgraph.operators import triangles as T
from partgraph.sources.graphs import PartitionedGraph


def _plain(sets, sg):
    for a, b, c in itertools.combinations(sorted(sets), 3):
        x, y, z = (sets[v] for v in (a, b, c))
        if x & y and y & z and x & z:
            p, q, r = (sg[v] for v in (a, b, c))
            same = sum(s is not None and s == t for s, t in ((p, q), (q, r), (p, r)))
            yield a, b, c, "i" if same == 3 else "ii" if same else "iii"


def _pages(folder):
    """(folder, addresses of each page, its language): 90 pages with five sets of addresses."""
    rnd, sets, sg, rows = random.Random(4), {}, {}, []
    kinds = [("p", "q"), ("q", "r"), ("r", "p"), ("s",), ("s", "p", "q", "r")]
    for v in rnd.sample(range(10**6), 90):
        items, sg[v] = rnd.choice(kinds), rnd.randrange(4)
        sets[v] = set(items)
        lang = ("other", "en", "fr", "de")[sg[v]]
        rows.append((v, f"http://x/{lang}/{v}", " ".join(f'<a href="http://{k}/">' for k in items)))
    return folder, sets, sg, rows


def _no_row_through_python(spark, tmp_path, name):
    folder, sets, sg, rows = _pages(str(tmp_path))
    spark.createDataFrame(rows, "page_id long, url string, html string").write.parquet(f"{folder}/pages.parquet")
    df = entry.queries()[name](spark, folder)
    got = [tuple(r) for r in df.collect()]
    assert len(got) == len(set(got)) and set(got) == set(_plain(sets, sg))
    # listed triangles came out of Python, those of a cell or a subgraph in one table
    assert "FlatMapGroups" not in df._jdf.queryExecution().optimizedPlan().toString()


def test_list_of_alike_pages(spark, tmp_path):
    _no_row_through_python(spark, tmp_path, "tri_list_page_colink")


def test_kernel_list_of_alike_pages(spark, tmp_path):
    _no_row_through_python(spark, tmp_path, "tri_kernel_list_page_colink")


@pytest.mark.parametrize(("vertices", "block"), [(60, 2), (60, 32), (9, 32)])
def test_classes_equal_plain_loops(spark, monkeypatch, vertices, block):
    """Small blocks, an owner null (equal to no other), null items, and few vertices that are all unlike."""
    monkeypatch.setattr(T, "LISTED_BLOCK", block)
    rnd = random.Random(vertices)
    kinds = [{1, 2}, {2, 3}, {4}, {1, 4}] if vertices > 9 else [{i, i + 1} for i in range(9)] + [{1, 5, 8}]
    sets = {v * 10**13 - 7: rnd.choice(kinds) if vertices > 9 else kinds[v] for v in range(vertices)}
    sg = {v: rnd.choice([0, 1, None]) for v in sets}
    edges = [(a, b, 1) for a, b in itertools.combinations(sorted(sets), 2) if sets[a] & sets[b]]
    g = PartitionedGraph(spark.createDataFrame(list(sg.items()), "vid long, sg long"), spark.createDataFrame(edges, "src long, dst long, weight long"))
    members = [(v, i) for v, items in sets.items() for i in items] * 2 + [(min(sets), None), (None, 1)]
    got = [tuple(r) for r in T.triangles_of_sets(g, spark.createDataFrame(members, "vid long, item long"), T.triangles).collect()]
    assert len(got) == len(set(got)) and set(got) == set(_plain(sets, sg))
