"""Line dedup against a plain loop over all pairs of lines."""

import itertools
import random

from pyspark.sql import functions as F

from partgraph.llm import line_dedup as L


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def edited(rnd, text, letters, k):
    b = list(text)
    for _ in range(k):
        kind, i = rnd.random(), rnd.randrange(len(b) + 1)
        if kind < 0.34:
            b.insert(i, rnd.choice(letters))
        elif b and kind < 0.67:
            b.pop(min(i, len(b) - 1))
        elif b:
            b[min(i, len(b) - 1)] = rnd.choice(letters)
    return "".join(b)


def test_bit_parallel_distance(spark):
    rnd = random.Random(5)
    letters = "abcé😀 "
    rows = []
    for _ in range(400):
        a = "".join(rnd.choice(letters) for _ in range(rnd.choice([0, 1, 5, 15, 16, 29, 30, 31, 60])))
        rows.append((a, edited(rnd, a, letters, rnd.randint(0, 4))))
    got = spark.createDataFrame(rows, "a string, b string").select("a", "b", L.near(F.col("a"), F.col("b")).alias("near")).collect()
    for r in got:
        assert r.near == (distance(r.a, r.b) <= min(2, min(len(r.a), len(r.b)) * 2 // 30)), (r.a, r.b)


def brute(rows):
    word = lambda x: x.strip(" \t\n\v\f\r")
    first, gone = {}, set()
    for d, t in rows:
        for p, line in enumerate((t or "").split("\n")):
            k = (d is not None, d or 0, p)
            if word(line) and (line not in first or k < first[line]):
                first[line] = k
    for a, b in itertools.combinations(first, 2):
        allowed = min(2, min(len(a), len(b)) * 2 // 30)
        if allowed and abs(len(a) - len(b)) <= allowed and distance(a, b) <= allowed:
            gone.add(a if first[a] > first[b] else b)
    keep = lambda d, p, x: not word(x) or (x not in gone and (d is not None, d or 0, p) == first[x])
    return {(d, t): None if t is None else "\n".join(x for p, x in enumerate(t.split("\n")) if keep(d, p, x)) for d, t in rows}, gone


def test_equals_all_pairs_with_odd_rows_and_clashing_names(spark):
    rnd = random.Random(3)
    base = ["".join(rnd.choice("abcdefgh é") for _ in range(rnd.choice([8, 14, 15, 16, 28, 29, 30, 31, 32, 36, 38, 46, 60, 200]))) for _ in range(30)]
    rows = [(d, "\n".join(edited(rnd, rnd.choice(base), "abcxyz😀", rnd.choice([0, 0, 1, 2, 2, 3])) for _ in range(rnd.randint(1, 4)))) for d in range(60)]
    rows += [(None, rows[3][1]), (500, None), (501, ""), (502, " \n \n"), (rows[3][0], rows[3][1])]
    want, gone = brute(rows)
    assert gone
    df = spark.createDataFrame([(*r, 1, 2, "z", "y") for r in rows], "doc_id long, text string, removed int, n_lines int, k string, `a.b` string")
    got = L.dedup_lines(df).collect()
    assert len(got) == len(rows) and all(r.removed == 1 and r.k == "z" and r["a.b"] == "y" for r in got)
    for r in got:
        assert r.text in [v for (d, _), v in want.items() if d == r.doc_id]
    assert L.filter_lines(df).columns == df.columns
    assert L.dedup_lines(df.limit(0)).count() == 0


def test_hot_signatures_are_split_without_loss(spark, monkeypatch):
    monkeypatch.setattr(L, "SPLIT", 3)
    rnd = random.Random(8)
    head = "the same beginning of many lines, "
    rows = [(i, head + "".join(rnd.choice("abc") for _ in range(20))) for i in range(40)]
    rows += [(100 + i, rows[i][1] + "x") for i in range(10)]
    want, _ = brute(rows)
    got = {r.doc_id: r.text for r in L.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {d: v for (d, _), v in want.items()}


def _join_rows(spark, run):
    """The largest number of rows that a join made while ``run`` ran."""
    store = spark._jsparkSession.sharedState().statusStore()
    seen = store.executionsCount()
    run()
    made = 0
    ids = store.executionsList()
    for i in range(seen, ids.size()):
        k = ids.apply(i).executionId()
        values, nodes = store.executionMetrics(k), store.planGraph(k).allNodes()
        for n in (nodes.apply(j) for j in range(nodes.size())):
            metrics = n.metrics()
            for m in (metrics.apply(j) for j in range(metrics.size())):
                if "Join" in n.name() and m.name() == "number of output rows" and values.contains(m.accumulatorId()):
                    made = max(made, int(values.apply(m.accumulatorId()).replace(",", "")))
    return made


def test_near_copies_make_no_row_for_a_pair(spark):
    rnd = random.Random(4)
    base = "a house style line that is sent with every letter, version "
    rows = [(i, base + f"{i:03d}"[: rnd.choice([2, 3])] + "abcdefghij"[i % 10] * (i % 2)) for i in range(200)]
    want, gone = brute(rows)
    got = {}
    most = _join_rows(spark, lambda: got.update({r.doc_id: r.text for r in L.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}))
    assert gone and got == {d: v for (d, _), v in want.items()}
    # 7,000 pairs and more are near; each line has a dozen signatures
    assert 0 < most <= 20 * len(rows), most


def test_filters_keep_all_near_pairs(spark):
    rnd = random.Random(6)
    rows = []
    for _ in range(500):
        a = "".join(rnd.choice("ab12é😀 ") for _ in range(rnd.choice([15, 30, 60])))
        rows.append((a, edited(rnd, a, "ab12é😀 ", 1)))
    masks = lambda c: F.array(L._odd_letters(F.col(c)), *L._odd_pairs(F.col(c)))
    flips = F.zip_with(masks("a"), masks("b"), lambda x, y: F.bit_count(x.bitwiseXOR(y)))
    for r in spark.createDataFrame(rows, "a string, b string").select("a", "b", flips.alias("f")).collect():
        gap = abs(len(r.a) - len(r.b))
        assert r.f[0] <= 2 - gap and r.f[1] + r.f[2] <= 4 - gap, r
