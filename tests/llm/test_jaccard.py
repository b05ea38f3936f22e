"""Chosen-path join against all pairs."""

import random
import re

from partgraph.llm import jaccard_join as J


def brute(texts):
    sets = []
    for t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        sets.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} or ({tuple(w)} if w else set()))
    n = [0] * len(texts)
    for i in range(len(sets)):
        for j in range(len(sets)):
            if i != j and (sets[i] == sets[j] or (sets[i] and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]))):
                n[i] += 1
    return n


def corpus(seed, copies):
    rnd = random.Random(seed)
    vocab = [f"w{i}" for i in range(300)]
    texts = [None, "", "a b", "a b", "a c"]
    shared = [rnd.choice(vocab) for _ in range(30)]
    for g in range(12):
        base = [rnd.choice(vocab) for _ in range(rnd.randint(20, 200))] + shared
        for _ in range(rnd.randint(1, copies)):
            w = list(base)
            for _ in range(rnd.randint(0, 6)):
                w[rnd.randrange(len(w))] = rnd.choice(vocab)
            texts.append(" ".join(w))
    return texts


def test_links_equal_brute_force(spark, monkeypatch):
    monkeypatch.setattr(J, "BUCKET", 6)
    texts = corpus(1, 14)
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r for r in J.near_duplicates(df)[0].collect()}
    assert [got[i].n_links for i in range(len(texts))] == brute(texts)
    assert all(got[i].class_id <= i for i in got)
    kept = J.keep_one(df.withColumn("cid", df.doc_id))
    assert kept.columns == ["doc_id", "text", "cid"]
    assert sorted(r.doc_id for r in kept.collect()) == sorted({r.class_id for r in got.values()})
    assert J.keep_one(df.limit(0)).count() == 0


def test_unrelated_rows_with_null_and_equal_ids(spark):
    one = lambda c: " ".join(f"{c}{i}" for i in range(30))
    rows = [(None, one("a")), (None, one("b")), (None, one("b") + " more"), (7, one("c")), (7, one("d")), (8, one("d")), (9, one("e"))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    kept = sorted((r.doc_id or 0, r.text[0]) for r in J.keep_one(df).collect())
    assert kept == [(0, "a"), (0, "b"), (7, "c"), (7, "d"), (9, "e")]
    got = J.near_duplicates(df)[0].collect()
    assert len({r.class_id for r in got}) == len({r.comp for r in got}) == 5
    assert {r.class_id for r in got if r.doc_id == 9} == {9}
