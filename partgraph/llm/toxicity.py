"""Toxicity by non-negative positive-unlabelled learning in numpy.

Confirmed toxic rows are the positives; a bounded sample of all documents outside the held-out fold, whatever their label
or without one, is the unlabelled set. The risk takes the positives' share (the class prior, from the labels) out of the
unlabelled loss and never lets the rest become negative: when it does, the step climbs back. Features are the presence of
a word, or of a word beginning of 4, 5, 6 or 8 bytes, that the positives hold significantly more often; there is no
bound on their number.

Cases: null and empty texts have no features and get the bias alone; without positives or labels each score is 0;
repeated texts count once in the fit; null doc_ids are in no fold that learns and are scored; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, chunks, forget, spill

#: Bounds of the fit: rows of each kind.
MAX_POSITIVE, MAX_UNLABELLED = 4000, 12_000
#: Standard errors by which the positives must hold a feature more often.
SURE = 5
PREFIXES = (4, 5, 6, 8)
THRESHOLD = 0.3
STEPS, RATE, DECAY = 300, 0.05, 2e-4
_TO_SPACE = bytes(b if b >= 0x80 or chr(b).isalnum() else 0x20 for b in range(256))


def marks_of(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """(text number, hash) of every lower-case word and of its beginnings; repeats included."""
    w = Words([(t or "").lower().encode("utf-8", "surrogatepass").translate(_TO_SPACE).decode("utf-8", "surrogatepass") for t in texts])
    own, size = w.owner(), w.end - w.start
    owns, hashes = [own], [w.hash]
    for k in PREFIXES:
        long = size > k
        owns.append(own[long])
        hashes.append(w.hash_of(w.start[long], w.start[long] + k) ^ np.uint64(k))
    return np.concatenate(owns), np.concatenate(hashes).view(np.int64)


def distinct_marks(own: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.lexsort((h, own))
    own, h = own[order], h[order]
    head = np.ones(len(h), bool)
    head[1:] = (own[1:] != own[:-1]) | (h[1:] != h[:-1])
    return own[head], h[head]


class Sparse:
    """Rows of flags and a last column of ones, as the places of the flags."""

    def __init__(self, row: np.ndarray, col: np.ndarray, rows: int, cols: int):
        self.row, self.col, self.rows, self.cols = row, col, rows, cols

    @classmethod
    def of(cls, x: np.ndarray | Sparse) -> Sparse:
        return x if isinstance(x, Sparse) else cls(*np.nonzero(x), *x.shape)

    def times(self, w: np.ndarray) -> np.ndarray:
        return np.bincount(self.row, w[self.col], self.rows) + w[-1]

    def turned(self, g: np.ndarray) -> np.ndarray:
        return np.append(np.bincount(self.col, g[self.row], self.cols), g.sum())


def fit_nnpu(pos: Sparse | np.ndarray, unl: Sparse | np.ndarray, prior: float) -> tuple[np.ndarray, float]:
    """Weights and bias of the least non-negative risk under the logistic loss (Adam, full batches); rows of flags."""
    pos, unl = Sparse.of(pos), Sparse.of(unl)
    w = np.zeros(pos.cols + 1)
    m, v = np.zeros_like(w), np.zeros_like(w)
    sig = lambda z: 1 / (1 + np.exp(-np.clip(z, -40, 40)))
    for step in range(1, STEPS + 1):
        zp, zu = pos.times(w), unl.times(w)
        negative = np.logaddexp(0, zu).mean() - prior * np.logaddexp(0, zp).mean()
        g_negative = unl.turned(sig(zu)) / unl.rows - prior * pos.turned(sig(zp)) / pos.rows
        g_positive = prior * pos.turned(sig(zp) - 1) / pos.rows
        g = g_positive + g_negative if negative >= 0 else -g_negative
        g[:-1] += DECAY * w[:-1]
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        w -= RATE * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    return w[:-1], float(w[-1])


def learn(docs: DataFrame, labels: DataFrame, in_fold) -> tuple[np.ndarray, np.ndarray, float]:
    """Sorted feature hashes, their weights and the bias, from rows where ``in_fold`` holds (a condition on doc_id)."""
    import pyarrow as pa

    rows = labels.where(in_fold & F.col("doc_id").isNotNull() & F.col("toxic").isNotNull())
    prior = rows.agg(F.avg(F.col("toxic").cast("double"))).first()[0]
    none = np.zeros(0, np.int64), np.zeros(0), -40.0
    if not prior:
        return none
    deal = F.xxhash64("doc_id", F.lit(11))
    pos = rows.where("toxic = 1").select("doc_id").distinct().orderBy(deal).limit(MAX_POSITIVE).withColumn("kind", F.lit(1))
    unl = docs.where(in_fold & F.col("doc_id").isNotNull()).select("doc_id").distinct().orderBy(deal).limit(MAX_UNLABELLED).withColumn("kind", F.lit(0))
    ids = F.broadcast(pos.unionByName(unl))  # at most MAX_POSITIVE + MAX_UNLABELLED ids
    text = F.coalesce("text", F.lit(""))
    sample = docs.select("doc_id", text.alias("text")).join(ids, "doc_id").select("kind", F.xxhash64("text").alias("h"), "text")
    sample = spill(sample.dropDuplicates(["kind", "h"]))
    keys = {k: np.sort(np.array([r[0] for r in sample.where(f"kind = {k}").select("h").collect()], np.int64)) for k in (0, 1)}
    n_pos, n_unl = len(keys[1]), len(keys[0])
    if not n_pos or not n_unl:
        return none

    def counted(batches):
        for batch in batches:
            texts, kind = batch.column("text").to_pylist(), np.asarray(batch.column("kind"))
            for a, b in chunks(texts):
                own, h = distinct_marks(*marks_of(texts[a:b]))
                mark, at = np.unique(h, return_inverse=True)
                p = np.bincount(at, kind[a:b][own], len(mark)).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(mark), pa.array(p), pa.array(np.bincount(at, minlength=len(mark)) - p)], ["mark", "p", "u"])

    counts = sample.select("kind", "text").mapInArrow(counted, "mark bigint, p bigint, u bigint").groupBy("mark").agg(F.sum("p").alias("p"), F.sum("u").alias("u"))
    share = (F.col("p") + F.col("u")) / (n_pos + n_unl)
    sure = (F.col("p") / n_pos - F.col("u") / n_unl) / F.sqrt(share * (1 - share) * (1 / n_pos + 1 / n_unl))
    best = counts.where("p > 1").where(sure >= SURE).select("mark").collect()
    marks = np.sort(np.array([r[0] for r in best], np.int64))

    def found(batches):
        for batch in batches:
            texts = batch.column("text").to_pylist()
            for a, b in chunks(texts):
                own, at = hits(texts[a:b], marks)
                take = pa.array(own + a)
                yield pa.RecordBatch.from_arrays([batch.column("kind").take(take), batch.column("h").take(take), pa.array(at.astype(np.int32))], ["kind", "h", "at"])

    grid = {}
    got = sample.mapInArrow(found, "kind int, h bigint, at int").toArrow()
    kind, h, at = (np.asarray(got.column(c)) for c in ("kind", "h", "at"))
    for k, names in keys.items():
        mine = kind == k
        grid[k] = Sparse(np.searchsorted(names, h[mine]), at[mine].astype(np.int64), len(names), len(marks))
    weights, bias = fit_nnpu(grid[1], grid[0], float(prior))
    forget(sample)
    return marks, weights, bias


def hits(texts: list[str | None], marks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(text number, place in the sorted ``marks``), once each."""
    if not len(marks):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    own, h = marks_of(texts)
    at = np.minimum(np.searchsorted(marks, h), len(marks) - 1)
    hit = marks[at] == h
    return distinct_marks(own[hit], at[hit])


def score(docs: DataFrame, model: tuple[np.ndarray, np.ndarray, float]) -> DataFrame:
    """doc_id and score of each whole text."""
    import pyarrow as pa

    marks, weights, bias = model

    def run(batches):
        for batch in batches:
            texts = batch.column("text").to_pylist()
            for a, b in chunks(texts):
                own, at = hits(texts[a:b], marks)
                z = np.bincount(own, weights[at], b - a) + bias
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(a, b - a), pa.array(1 / (1 + np.exp(-np.clip(z, -700, 700))))], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").mapInArrow(run, "doc_id bigint, score double")


def op10_nnpu_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    fold = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 4 == 2, F.lit(False))
    model = learn(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), ~fold)
    return score(docs, model).select("doc_id", fold.alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
