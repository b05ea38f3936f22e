"""Quality counts against plain Python, and what the adaptive rules keep."""

import re

from partgraph.llm import quality as Q

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def counts(text):
    w = WORD.findall(text or "")
    lines = [x for x in (text or "").split("\n") if WORD.search(x)]
    windows = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
    covered = set()
    for i, x in enumerate(windows):
        if windows.count(x) > 1:
            covered.update(range(i, i + 5))
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text or ""), len(lines) - len(set(lines)), len(covered)


def made():
    import random

    rnd = random.Random(2)
    vocab = ["stone", "river", "été", "a", "bread😀", "light"]
    docs = [" ".join(rnd.choice(vocab) for _ in range(rnd.randint(20, 60))) + "\nlast line\nlast line" for _ in range(60)]
    return docs + [None, "", " \n\t", "a b c", "one two three four five " * 6, "x y z\x0bq", "## ** $$ %% && || << >> #a *b $c"]


def test_counts_and_base_rule(spark):
    texts = made()
    df = spark.createDataFrame([(i, t, "en" if i % 2 else None, "s") for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string")
    got = {r.doc_id: r for r in Q.verdicts(df, "doc_id").collect()}
    for i, t in enumerate(texts):
        want = counts(t)
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want, (t, want)
        assert r.base_failed == (want[0] < 10 or 100 * want[4] > 20 * want[0])
        assert not (r.base_failed and r.kept)


def test_limits_follow_their_group(spark):
    """Long words are usual in one language and odd in the other."""
    short, long = "ab cd ef gh ij kl mn op qr st uv", "abcdefghijkl mnopqrstuvwx yzabcdefghij klmnopqrstuv wxyzabcdefgh ijklmnopqrst uvwxyzabcdef ghijklmnopqr stuvwxyzabcd efghijklmnop qrstuvwxyzab"
    rows = [(i, short + f" {i % 7}a", "xx", "s") for i in range(900)] + [(1000 + i, long + f" {i % 7}a", "yy", "s") for i in range(900)] + [(5000, long, "xx", "s"), (5001, short, "yy", "s")]
    got = {r.doc_id: r.kept for r in Q.verdicts(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string"), "doc_id").collect()}
    assert not got[5000] and not got[5001] and all(v for k, v in got.items() if k < 5000)


def test_filter_keeps_columns_and_rows(spark):
    rows = [(1, "plain words of a text that is long enough to stay in here", "en", "s", 1), (1, "plain words of a text that is long enough to stay in here", "en", "s", 2), (None, None, None, None, 3), (3, "too short", "en", "s", 4)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_words int")
    kept = Q.filter_documents(df)
    assert kept.columns == df.columns and sorted(r.n_words for r in kept.collect()) == [1, 2]
    assert Q.filter_documents(df.limit(0)).count() == 0
    assert Q.verdicts(df.limit(0), "doc_id").count() == 0


def test_verdicts_on_the_labelled_sample(spark):
    sf = "/root/testdata/sf0.01"
    got = Q.op3_adaptive_quality(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id")
    bad = got.where("quality = 0").count()
    assert got.where("quality = 0 and not kept").count() >= 0.9 * bad > 0
    assert got.where("quality = 1 and not base_failed and not kept").count() == 0
