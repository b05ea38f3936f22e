"""Substring dedup: windows of WINDOW words that start anywhere else, found by FM-indexes over content shards.

Equal windows share their least ANCHOR-word hash, so a document is cut into runs of windows with one such anchor, and
runs are dealt by anchor. Anchors met at one place only cannot repeat and never leave their row. The runs of a shard form one
FM-index; each run streams through it by batched backward search and reports the windows that occur twice or more.

Runs of an anchor that more than HOT runs share (a passage in a large part of all documents) would meet in one task;
their windows are counted by 128-bit fingerprints with partial aggregation instead. Texts that occur in more than one
row repeat as a whole and are indexed once.

Cases: a null or empty text has no words; documents shorter than WINDOW words lose nothing; repeated rows repeat each
other; a null doc_id is a value like others; other columns are kept by ``filter_substrings``.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, chunks, mix, partitions
from .fm_index import FMIndex, repeated_spans

WINDOW = 35
ANCHOR = 6
HOT = 4000
#: Words of one FM-index, about; a shard with more is indexed part by part, at anchor borders.
INDEX_WORDS = 300_000
KEY = ["h", "c", "doc_id"]


def runs_of(w: Words, window: int, anchor: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Anchor hash, first window (flat word number), number of windows of each run, and whether it may repeat itself."""
    n = len(w.start) - window + 1
    if n <= 0:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, bool)
    with np.errstate(over="ignore"):
        g = np.zeros(len(w.start) - anchor + 1, np.uint64)
        for j in range(anchor):
            g = g * np.uint64(0xD6E8FEB86659FD93) + w.hash[j : j + len(g)]
        g = mix(g)
    order = np.argsort(g, kind="stable")
    twin = np.zeros(len(g) + 1, np.int64)  # places whose anchor words follow again
    twin[order[:-1][g[order[1:]] == g[order[:-1]]] + 1] = 1
    twins = np.cumsum(twin)
    span, have = window - anchor + 1, 1
    while have * 2 <= span:
        g = np.minimum(g[:-have], g[have:])
        have *= 2
    if span > have:
        g = np.minimum(g[: len(g) - (span - have)], g[span - have :])
    own = w.owner()
    at = np.flatnonzero(own[:n] == own[window - 1 :])
    if not len(at):
        return np.zeros(0, np.uint64), at, at, np.zeros(0, bool)
    value, doc = g[at], own[at]
    head = np.concatenate([[True], (value[1:] != value[:-1]) | (doc[1:] != doc[:-1])])
    first = np.flatnonzero(head)
    start, size = at[first], np.diff(np.append(first, len(at)))
    return value[first], start, size, twins[start + size + span - 1] > twins[start]


def _keyed(docs: DataFrame) -> DataFrame:
    text = F.coalesce("text", F.lit(""))
    return docs.select(F.xxhash64(text).alias("h"), F.crc32(text).alias("c"), F.col("doc_id").cast("bigint").alias("doc_id"), text.alias("text"))


def anchors(keyed: DataFrame, window: int) -> DataFrame:
    """(h, anchor, start, windows, again): the runs of each text.

    Texts that differ but share ``h`` get each other's runs, which the search then turns down.
    """
    import pyarrow as pa

    def run(batches):
        for batch in batches:
            texts = batch.column("text").to_pylist()
            for a, b in chunks(texts):
                w = Words(texts[a:b])
                value, at, size, again = runs_of(w, window, ANCHOR)
                doc = np.searchsorted(w.first, at, "right") - 1
                take = pa.array(doc + a)
                yield pa.RecordBatch.from_arrays(
                    [batch.column("h").take(take), pa.array(value.view(np.int64)), pa.array((at - w.first[doc]).astype(np.int32)), pa.array(size.astype(np.int32)), pa.array(again)],
                    ["h", "anchor", "start", "windows", "again"],
                )

    return keyed.select("h", "text").mapInArrow(run, "h bigint, anchor bigint, start int, windows int, again boolean")


def _slices(batches, window: int):
    """Text slices of the candidate runs, and window fingerprints of hot ones."""
    import pyarrow as pa

    names = [*KEY, "anchor", "start", "words", "f1", "f2"]
    for batch in batches:
        texts, lists = batch.column("text").to_pylist(), batch.column("runs")
        for a, b in chunks(texts, 1 << 20):
            w = Words(texts[a:b])
            f1 = f2 = None
            cols: list[list] = [[] for _ in range(6)]
            for i, found in enumerate(lists.slice(a, b - a).to_pylist()):
                base, limit = int(w.first[i]), int(w.first[i + 1])
                for r in found:
                    s, e = base + r["start"], base + r["start"] + r["windows"] + window - 1
                    if e > limit:  # a run of another text with the same hash
                        continue
                    if not r["hot"]:
                        for col, x in zip(cols, (a + i, r["anchor"], r["start"], w.data[w.start[s] : w.end[e - 1]].tobytes(), None, None), strict=True):
                            col.append(x)
                        continue
                    if f1 is None:
                        f1, f2 = _fingerprints(w.hash, window, 0xD6E8FEB86659FD93), _fingerprints(w.hash, window, 0xA0761D6478BD642F)
                    k = r["windows"]
                    for col, x in zip(cols, ([a + i] * k, [None] * k, range(r["start"], r["start"] + k), [None] * k, f1[s : s + k].tolist(), f2[s : s + k].tolist()), strict=True):
                        col.extend(x)
            take = pa.array(cols[0], pa.int64())
            yield pa.RecordBatch.from_arrays([*(batch.column(k).take(take) for k in KEY), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.int32()), pa.array(cols[3], pa.binary()), pa.array(cols[4], pa.int64()), pa.array(cols[5], pa.int64())], names)


def _fingerprints(h: np.ndarray, window: int, factor: int) -> np.ndarray:
    n = max(0, len(h) - window + 1)
    with np.errstate(over="ignore"):
        f = np.zeros(n, np.uint64)
        for j in range(window):
            f = f * np.uint64(factor) + h[j : j + n]
        return mix(f).view(np.int64)


def search_shard(slices: list[bytes], window: int) -> tuple[np.ndarray, np.ndarray]:
    """(slice, window start) hits among the slices of one shard: equal slices are indexed each but searched once."""
    w = Words([])
    w.data = np.frombuffer(b" ".join(slices) + b" ", np.uint8)
    full = Words.__new__(Words)
    full.data, full._hash = w.data, None
    full.offset = np.concatenate([[0], np.cumsum([len(s) + 1 for s in slices])])
    space = np.isin(full.data, np.array([0x20, *range(0x09, 0x0E)], np.uint8))
    edge = np.flatnonzero(np.diff(np.concatenate([[True], space]).astype(np.int8)))
    full.start, full.end = edge[0::2], edge[1::2]
    full.first = np.searchsorted(full.start, full.offset)
    _, ids = np.unique(full.hash, return_inverse=True)
    sizes = full.counts()
    at = full.first[:-1] + np.arange(len(slices))  # one border symbol before each slice
    symbols = np.zeros(len(ids) + len(slices), np.int64)
    keep = np.ones(len(symbols), bool)
    keep[at] = False
    symbols[keep] = ids + 1
    index = FMIndex(symbols, window)
    own: dict[bytes, int] = {}
    group = np.fromiter((own.setdefault(s, len(own)) for s in slices), np.int64, len(slices))
    _, lead = np.unique(group, return_index=True)
    who, start = repeated_spans(index, symbols, at[lead] + 1, sizes[lead], window)
    order = np.argsort(who, kind="stable")
    who, start = who[order], start[order]
    left, right = np.searchsorted(who, group), np.searchsorted(who, group, "right")
    n = right - left
    flat = np.repeat(left, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
    return np.repeat(np.arange(len(slices)), n), start[flat]


def _search(batches, window: int):
    import pyarrow as pa

    held: list[pa.RecordBatch] = []
    words = 0

    def flush(table: pa.Table):
        who, at = search_shard(table.column("words").to_pylist(), window)
        if len(who):
            got = table.select([*KEY, "start"]).take(pa.array(who)).combine_chunks()
            start = np.asarray(got.column("start")).astype(np.int64) + at
            yield from pa.table([*(got.column(k) for k in KEY), pa.array(start.astype(np.int32))], [*KEY, "start"]).to_batches()

    for batch in batches:
        held.append(batch)
        words += batch.column("words").nbytes // 6
        if words >= INDEX_WORDS:
            table = pa.Table.from_batches(held)
            anchor = np.asarray(table.column("anchor"))
            cut = int(np.searchsorted(anchor, anchor[-1]))
            if cut:
                yield from flush(table.slice(0, cut))
                held = table.slice(cut).to_batches()
                words = table.slice(cut).column("words").nbytes // 6
    if held and sum(map(len, held)):
        yield from flush(pa.Table.from_batches(held))


def repeated_windows(docs: DataFrame, window: int = WINDOW) -> tuple[DataFrame, DataFrame]:
    """(keyed documents, per (h, c, doc_id): spans of repeated windows or whole = true)."""
    spark = docs.sparkSession
    n = partitions(spark)
    keyed = _keyed(docs)
    rows = keyed.select("h", "c", "doc_id")
    texts = rows.groupBy("h", "c").agg(F.count("*").alias("copies"), F.min("doc_id").alias("lead"))
    runs = anchors(keyed, window)
    met = runs.groupBy("anchor").agg(F.count("*").alias("met"), F.min("h").alias("low"), F.max("h").alias("high"), F.max("again").alias("any_again"))
    met = met.where("low <> high or any_again").select("anchor", (F.col("met") > HOT).alias("hot"))
    shared = runs.join(met, "anchor").select("h", F.struct("anchor", "start", "windows", "hot").alias("run"))
    wanted = shared.groupBy("h").agg(F.collect_set("run").alias("runs")).join(texts, "h").select("h", "c", "lead", "runs")

    def cut(hot: bool) -> DataFrame:
        mine = wanted.withColumn("runs", F.filter("runs", lambda r: r["hot"] if hot else ~r["hot"])).where(F.size("runs") > 0)
        met = _with_spans(keyed, mine.withColumnsRenamed({"lead": "doc_id"}), "runs", how="inner")
        return met.select(*KEY, "text", "runs").mapInArrow(lambda b: _slices(b, window), "h bigint, c bigint, doc_id bigint, anchor bigint, start int, words binary, f1 bigint, f2 bigint")

    dealt = cut(hot=False).select(*KEY, "anchor", "start", "words").repartition(n, "anchor").sortWithinPartitions("anchor")
    found = dealt.mapInArrow(lambda b: _search(b, window), "h bigint, c bigint, doc_id bigint, start int")
    marks = cut(hot=True).select(*KEY, "start", "f1", "f2")
    twice = marks.groupBy("f1", "f2").agg(F.count("*").alias("k")).where("k > 1").select("f1", "f2")
    hot = marks.join(twice, ["f1", "f2"]).select(*KEY, "start")
    spans = found.unionByName(hot).groupBy(*KEY).agg(F.collect_set("start").alias("starts")).withColumn("whole", F.lit(False))
    copied = texts.where("copies > 1").select("h", "c")
    whole = rows.join(copied, ["h", "c"]).distinct().select(*KEY, F.lit(None).cast("array<int>").alias("starts"), F.lit(True).alias("whole"))
    return keyed, spans.unionByName(whole).groupBy(*KEY).agg(F.first("starts", True).alias("starts"), F.max("whole").alias("whole"))


def _mask(n: int, starts, whole: bool, window: int) -> np.ndarray:
    gone = np.zeros(n + 1, np.int64)
    if whole and n >= window:
        gone[0], gone[n] = 1, -1
    elif starts:
        s = np.asarray(starts)
        np.add.at(gone, s, 1)
        np.add.at(gone, s + window, -1)
    return np.cumsum(gone)[:-1] > 0


def _with_spans(keyed: DataFrame, spans: DataFrame, *columns: str, how: str = "left") -> DataFrame:
    """``keyed`` with ``columns`` of the row in ``spans`` that has its (h, c, doc_id); equal exchanges of texts are reused."""
    right = spans.select(*[F.col(k).alias(f"__{k}") for k in KEY], *columns)
    same = (keyed["h"] == right["__h"]) & (keyed["c"] == right["__c"]) & keyed["doc_id"].eqNullSafe(right["__doc_id"])
    return keyed.join(right, same, how).drop(*[f"__{k}" for k in KEY])


def op1_fm_substrings(spark, sf_dir: str) -> DataFrame:
    import pyarrow as pa

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    keyed, spans = repeated_windows(docs)

    def run(batches):
        for batch in batches:
            n, removed, sha = [], [], []
            for text, starts, whole in zip(batch.column("text").to_pylist(), batch.column("starts").to_pylist(), batch.column("whole").to_pylist(), strict=True):
                words = (text or "").encode().split()  # bytes split on the same six characters
                gone = _mask(len(words), starts, bool(whole), WINDOW)
                n.append(len(words))
                removed.append(int(gone.sum()))
                if removed[-1]:
                    words = [x for x, g in zip(words, gone.tolist(), strict=True) if not g]
                sha.append(hashlib.sha256(b" ".join(words)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(removed, pa.int64()), pa.array(sha, pa.string())], ["doc_id", "n_words", "n_removed", "kept_sha256"])

    return _with_spans(keyed, spans, "starts", "whole").select("doc_id", "text", "starts", "whole").mapInArrow(run, "doc_id bigint, n_words bigint, n_removed bigint, kept_sha256 string")


def filter_substrings(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """The documents without their repeated windows, same columns; white space before kept words stays."""
    import pyarrow as pa

    _, spans = repeated_windows(docs, window)
    names = docs.columns
    schema = docs.schema

    def run(batches):
        for batch in batches:
            out = []
            for text, starts, whole in zip(batch.column("text").to_pylist(), batch.column("__starts").to_pylist(), batch.column("__whole").to_pylist(), strict=True):
                if text and (starts or whole):
                    w = Words([text])
                    gone = _mask(len(w.start), starts, bool(whole), window)
                    if gone.any():
                        begin = np.concatenate([[0], w.end[:-1]])
                        text = b"".join(w.data[a:b].tobytes() for a, b in zip(begin[~gone], w.end[~gone], strict=True)).decode().lstrip(" \t\n\v\f\r")
                out.append(text)
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.string()) if c == "text" else batch.column(c) for c in names], names)

    text = F.coalesce("text", F.lit(""))
    keyed = docs.select(F.struct(*names).alias("__row"), F.xxhash64(text).alias("h"), F.crc32(text).alias("c"), F.col("doc_id").cast("bigint").alias("doc_id"))
    met = _with_spans(keyed, spans.withColumnsRenamed({"starts": "__starts", "whole": "__whole"}), "__starts", "__whole")
    return met.select("__row.*", "__starts", "__whole").mapInArrow(run, schema)
