"""The pipeline stage by stage against the operators' own rules."""

import random

import corpus_pipeline as C


def corpus():
    rnd = random.Random(6)
    vocab = [f"w{i}" for i in range(400)]
    text = lambda n: " ".join(rnd.choice(vocab) for _ in range(n))
    passage = text(60)
    rows = [(i, "\n".join([text(40), text(30), "Licensed under the usual terms of the house."])) for i in range(30)]
    rows += [(100 + i, rows[i][1] + "\n" + text(3)) for i in range(5)]
    rows += [(200 + i, text(50) + "\n" + passage + " " + text(20)) for i in range(3)]
    rows += [(300, None), (301, ""), (302, "too short"), (None, text(60)), (None, text(70)), (303, "## $$ %% " * 20)]
    return [(d, t, "en", "s", len(t or ""), "x") for d, t in rows], passage


def test_stages(spark, tmp_path):
    rows, passage = corpus()
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, removed string").write.parquet(str(tmp_path / "documents.parquet"))
    docs = spark.read.parquet(str(tmp_path / "documents.parquet"))
    names = docs.columns
    seen = {}
    for name, stage in C.STAGES:
        docs = stage(spark, docs, str(tmp_path))
        docs.write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        seen[name] = docs.collect()
        if name != "best_fit_packing":
            assert docs.columns == names
    ids = lambda name: sorted(r.doc_id or -1 for r in seen[name])
    assert ids("quality_rules") == sorted(d or -1 for d, *_ in rows if d not in (300, 301, 302, 303))
    assert ids("line_dedup") == ids("quality_rules")
    house = [r for r in seen["line_dedup"] if "usual terms" in r.text]
    assert len(house) == 1 and all(r.n_chars == len(r.text) for r in seen["line_dedup"])
    assert all(r.removed == "x" for r in seen["substring_dedup"])
    # of the near copies, lines of the later ones went in the line stage; passages go in the substring stage
    held = [r for r in seen["ngram_jaccard_join"] if passage in r.text]
    assert not [r for r in seen["substring_dedup"] if passage in r.text] or len(held) < 2
    pieces = seen["best_fit_packing"]
    assert sorted({r.doc_id or -1 for r in pieces}) == sorted(set(ids("substring_dedup")))
    got = C.run(spark, str(tmp_path)).collect()
    assert sorted((r.doc_id or -1, r.piece, r.length, r.ids_crc32) for r in got) == sorted((r.doc_id or -1, r.piece, r.length, r.ids_crc32) for r in pieces)


def test_empty_table(spark, tmp_path):
    rows, _ = corpus()
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, removed string").limit(0).write.parquet(str(tmp_path / "documents.parquet"))
    assert C.run(spark, str(tmp_path)).count() == 0
