"""Quality rules with adaptive thresholds: mergeable quantile sketches for each language and source.

Each measure is an integer and falls into a log-linear bucket (relative width 1/32); bucket counts of a group are its
sketch. Counts add up, so sketches merge exactly in any order: partial aggregation merges them before the shuffle. Each
quantile of a group is drawn towards that of its language, and this one towards that of the whole corpus, with the weight
of SHRINK documents: large groups follow their own sketch, small ones are steadied by the wider ones.

Cases: null or empty text has no words and fails the base rule; a null language or source is a group of its own; ties
fall into one bucket; repeated rows count each; an empty table gives no rows; other columns are ignored by ``measure``
and kept by ``filter_documents``.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Words, chunks, spill, text_key

#: Fixed value: the characters that count as symbols.
SYMBOLS = "#*$%&|<>"
MIN_WORDS = 10
MAX_REPEAT_PERCENT = 20
WINDOW = 5
#: Sub-buckets of a power of two: thresholds are exact to 1/32.
SUB = 32
#: Documents' worth of the wider sketch in each quantile of a group.
SHRINK = 100
#: (measure, side, least spread): a document leaves when it is beyond median -/+ REACH spreads on that side.
#: A spread is the distance from the median to the quartile on that side. The least spread takes its place where most
#: documents have the same value, as with measures that are 0 in clean text.
RULES = (("symbol_rate", "high", 30), ("mark_rate", "high", 100), ("word_len", "high", 15), ("word_len", "low", 15), ("dup_line_rate", "high", 300), ("stutter_rate", "high", 80))
REACH = 16
DIGEST = "n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, n_lines bigint, n_marked bigint, n_stutter bigint"

_SYMBOL = np.zeros(256, bool)
_SYMBOL[[ord(c) for c in SYMBOLS]] = True
#: ASCII characters of prose: letters, digits, space and common punctuation. The rest of ASCII marks a word.
_PLAIN = np.zeros(256, bool)
_PLAIN[[*range(0x30, 0x3A), *range(0x41, 0x5B), *range(0x61, 0x7B), *range(0x80, 0x100), *map(ord, " \t\n\r\v\f.,;:'\"?()-/@_")]] = True


def features(texts: list[str | None]) -> dict[str, np.ndarray]:
    """The counts of each text."""
    w = Words(texts)
    n, data = len(texts), w.data
    words = w.counts().astype(np.int64)
    own = w.owner()

    def per_text(flags: np.ndarray) -> np.ndarray:
        return np.diff(np.concatenate([[0], np.cumsum(flags)])[w.offset])

    glyph = (data & 0xC0) != 0x80
    run = np.concatenate([[0], np.cumsum(glyph)])
    chars = np.bincount(own, (run[w.end] - run[w.start]).astype(np.float64), n).astype(np.int64)
    odd = np.concatenate([[0], np.cumsum(~_PLAIN[data])])
    marked = np.bincount(own[(odd[w.end] - odd[w.start]) > 0], minlength=n)
    h, at, doc = w.windows(WINDOW)
    covered = np.zeros(len(w.start) + 1, np.int64)
    if len(h):
        order = np.lexsort((h, doc))
        same = (h[order][1:] == h[order][:-1]) & (doc[order][1:] == doc[order][:-1])
        twice = at[order[np.concatenate([[False], same]) | np.concatenate([same, [False]])]]
        np.add.at(covered, twice, 1)
        np.add.at(covered, np.minimum(twice + WINDOW, len(w.start)), -1)
    repeat = np.bincount(own, (np.cumsum(covered)[:-1] > 0).astype(np.float64), n).astype(np.int64)
    again = np.flatnonzero((w.hash[1:] == w.hash[:-1]) & (own[1:] == own[:-1]))
    stutter = np.bincount(own[again], minlength=n)
    dup, lines = np.zeros(n, np.int64), np.zeros(n, np.int64)
    for i, t in enumerate(texts):
        if words[i]:
            with_word = [x for x in t.split("\n") if x.strip(" \t\n\v\f\r")]
            lines[i], dup[i] = len(with_word), len(with_word) - len(set(with_word))
    return {"n_words": words, "word_chars": chars, "n_symbols": per_text(_SYMBOL[data]).astype(np.int64), "n_dup_lines": dup, "n_repeat_words": repeat, "n_lines": lines, "n_marked": marked.astype(np.int64), "n_stutter": stutter.astype(np.int64)}


def measure(docs: DataFrame, *columns: str) -> DataFrame:
    """The named columns of ``docs`` and the counts of each whole text."""
    import pyarrow as pa

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column("text").to_pylist()
            for a, b in chunks(texts):
                got = features(texts[a:b])
                yield pa.RecordBatch.from_arrays([*(batch.column(c).slice(a, b - a) for c in columns), *map(pa.array, got.values())], [*columns, *got])

    kinds = dict(docs.dtypes)
    schema = ", ".join([*(f"`{c}` {kinds[c]}" for c in columns), DIGEST])
    return docs.select(*dict.fromkeys([*columns, "text"])).mapInArrow(run, schema)


def bucket(value: Column) -> Column:
    """Log-linear bucket of a non-negative integer, as the bucket's least value; exact integer arithmetic."""
    step = reduce(lambda c, e: c.when(value >= (SUB << e), F.lit(1 << e)), range(39, 0, -1), F.when(F.lit(False), F.lit(1))).otherwise(F.lit(1)).cast("bigint")
    return value - F.pmod(value, step)


def rates(measured: DataFrame) -> DataFrame:
    """Integer measures of the adaptive rules, per 10,000 (word_len: per 100)."""
    words = F.greatest("n_words", F.lit(1))
    return measured.withColumns({
        "symbol_rate": F.floor(F.col("n_symbols") * 10000 / F.greatest("word_chars", F.lit(1))),
        "mark_rate": F.floor(F.col("n_marked") * 10000 / words),
        "stutter_rate": F.floor(F.col("n_stutter") * 10000 / words),
        "word_len": F.floor(F.col("word_chars") * 100 / words),
        "dup_line_rate": F.floor(F.col("n_dup_lines") * 10000 / F.greatest("n_lines", F.lit(1))),
    })


def sketches(rated: DataFrame, names: list[str]) -> DataFrame:
    """Bucket counts (group_lang, group_source, measure, b, n): one row for each bucket of each group."""
    cells = rated.select("group_lang", "group_source", F.explode(F.array(*[F.struct(F.lit(m).alias("measure"), bucket(F.col(m)).alias("b")) for m in names])).alias("x"))
    return cells.groupBy("group_lang", "group_source", "x.measure", "x.b").agg(F.count("*").alias("n"))


def quantiles(sketch: DataFrame, by: list[str]) -> DataFrame:
    """Size, median and quartiles of the sketches merged by ``by``."""
    merged = sketch.groupBy(*by, "measure", "b").agg(F.sum("n").alias("n"))
    w = Window.partitionBy(*by, "measure")
    up = merged.withColumn("upto", F.sum("n").over(w.orderBy("b"))).withColumn("total", F.sum("n").over(w))
    at = lambda percent: F.min(F.when(F.col("upto") * 100 >= F.col("total") * percent, F.col("b")))
    return up.groupBy(*by, "measure").agg(F.max("total").alias("total"), at(25).alias("q25"), at(50).alias("q50"), at(75).alias("q75"))


def limits(sketch: DataFrame) -> DataFrame:
    """One row for each (group_lang, group_source) with a low and a high limit of each rule."""
    source = quantiles(sketch, ["group_lang", "group_source"])
    lang = quantiles(sketch, ["group_lang"])
    all_ = quantiles(sketch.withColumn("all", F.lit(1)), ["all"])
    wider = lambda df, p: df.select(*[c for c in df.columns if c.startswith("group")], "measure", *[F.col(c).alias(f"{p}_{c}") for c in ("total", "q25", "q50", "q75")])
    got = source.join(wider(lang, "l"), ["group_lang", "measure"]).join(wider(all_, "a"), ["measure"])
    drawn = lambda total, q, towards: F.expr(f"({total} * {q} + {SHRINK} * ({towards})) div ({total} + {SHRINK})")
    for q in ("q25", "q50", "q75"):
        got = got.withColumn(f"l_{q}", drawn("l_total", f"l_{q}", f"a_{q}"))
        got = got.withColumn(q, drawn("total", q, f"l_{q}"))
    cols = []
    for m, side, least in RULES:
        spread = F.greatest(F.col("q75") - F.col("q50") if side == "high" else F.col("q50") - F.col("q25"), F.lit(least))
        limit = F.col("q50") + REACH * spread if side == "high" else F.col("q50") - REACH * spread
        cols.append(F.max(F.when(F.col("measure") == m, limit)).alias(f"{m}_{side}"))
    return got.groupBy("group_lang", "group_source").agg(*cols)


def verdicts(docs: DataFrame, *columns: str) -> DataFrame:
    """The counts of each document, base_failed and kept, after ``columns``."""
    rated = rates(spill(measure(docs, *dict.fromkeys([*columns, "lang", "source"]))))
    rated = rated.withColumns({"group_lang": F.coalesce(F.col("lang").cast("string"), F.lit("\0")), "group_source": F.coalesce(F.col("source").cast("string"), F.lit("\0"))})
    sound = F.col("n_words") >= MIN_WORDS
    table = limits(sketches(rated.where(sound), list(dict.fromkeys(m for m, _, _ in RULES))))
    base = ~sound | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    within = reduce(lambda a, b: a & b, [F.coalesce(F.col(m) <= F.col(f"{m}_high") if side == "high" else F.col(m) >= F.col(f"{m}_low"), F.lit(True)) for m, side, _ in RULES])
    joined = rated.join(table, ["group_lang", "group_source"], "left")
    return joined.select(*columns, "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", base.alias("base_failed"), (~base & within).alias("kept"))


def op3_adaptive_quality(spark, sf_dir: str) -> DataFrame:
    return verdicts(spark.read.parquet(f"{sf_dir}/documents.parquet"), "doc_id")


def filter_documents(docs: DataFrame) -> DataFrame:
    """The documents that pass, with all their columns; rows equal in doc_id, language, source and text pass together."""
    key = ["doc_id", "lang", "source", "__text"]
    keyed = docs.withColumn("__text", text_key(F.col("text")))
    passed = verdicts(keyed, "doc_id", "lang", "source", "__text").where("kept").select(*[F.col(c).alias(f"__k_{c}") for c in key]).distinct()
    same = reduce(lambda a, b: a & b, [keyed[c].eqNullSafe(passed[f"__k_{c}"]) for c in key])
    return keyed.join(passed, same, "left_semi").select(*docs.columns)
