"""FM-index and substring dedup against brute force."""

import hashlib
import random
import re

import numpy as np
import pytest

from partgraph.llm import substring_dedup as S
from partgraph.llm.fm_index import FMIndex


def brute(texts, window):
    words = [re.findall(r"[^\x20\x09-\x0D]+", t or "") for t in texts]
    count = {}
    for w in words:
        for i in range(len(w) - window + 1):
            k = tuple(w[i : i + window])
            count[k] = count.get(k, 0) + 1
    out = []
    for w in words:
        gone = [False] * len(w)
        for i in range(len(w) - window + 1):
            if count[tuple(w[i : i + window])] > 1:
                gone[i : i + window] = [True] * window
        kept = [x for x, g in zip(w, gone) if not g]
        out.append((len(w), sum(gone), hashlib.sha256(" ".join(kept).encode()).hexdigest()))
    return out


def test_fm_counts():
    rng = np.random.default_rng(3)
    s = np.append(rng.integers(1, 5, 400), 0)
    fm = FMIndex(s, 8)
    t = s.tolist()
    for _ in range(200):
        a = int(rng.integers(0, 390))
        pat = t[a : a + int(rng.integers(1, 8))]
        lo, hi = np.zeros(1, np.int64), np.full(1, fm.n)
        for c in reversed(pat):
            lo, hi = fm.extend(np.array([c]), lo, hi)
        assert hi[0] - lo[0] == sum(t[i : i + len(pat)] == pat for i in range(len(t)))


def corpus(seed):
    rnd = random.Random(seed)
    vocab = [f"w{i}é" if i % 3 else f"w{i}" for i in range(60)]
    long = [rnd.choice(vocab) for _ in range(400)]
    texts = []
    for _ in range(40):
        parts = []
        for _ in range(rnd.randint(0, 4)):
            if rnd.random() < 0.5:
                a = rnd.randrange(380)
                piece = list(long[a : a + rnd.randint(5, 120)])
                if piece and rnd.random() < 0.5:
                    piece[rnd.randrange(len(piece))] = "changed"
                parts += piece
            else:
                parts += [rnd.choice(vocab) for _ in range(rnd.randint(0, 60))]
        texts.append(rnd.choice([" ", "\n", "\t "]).join(parts))
    texts += [None, "", "a", texts[0], " ".join(["x"] * 90), " ".join(["x", "y"] * 50)]
    return texts


@pytest.mark.parametrize("hot", [4000, 3])
def test_against_brute_force(spark, tmp_path, monkeypatch, hot):
    monkeypatch.setattr(S, "HOT", hot)
    texts = corpus(hot)
    d = tmp_path / "documents.parquet"
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(str(d))
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in S.op1_fm_substrings(spark, str(tmp_path)).collect()}
    assert got == dict(enumerate(brute(texts, S.WINDOW)))
    assert sum(v[1] for v in got.values()) > 0


def test_null_ids_repeats_and_empty(spark):
    t = " ".join(f"k{i}" for i in range(40))
    rows = [(None, t, 1), (None, t, 1), (5, "short one", 2), (6, None, 3)]
    df = spark.createDataFrame(rows, "doc_id long, text string, start int")
    out = sorted((r.text or "", r.start) for r in S.filter_substrings(df).collect())
    assert out == [("", 1), ("", 1), ("", 3), ("short one", 2)]
    assert S.filter_substrings(df.limit(0)).count() == 0
