"""Shared pieces of the training-data operators: words, hashes, spilled tables."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..storage import forget, shared_dir, spill  # noqa: F401  the operators take them from here

#: A word is a maximal run of code points outside these six (fixed value).
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
#: Bytes of text that one numpy step holds at once.
CHUNK_BYTES = 1 << 19

_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def text_key(col):
    """96 bits and the length of a text, as one struct to join and group on."""
    text = F.coalesce(col, F.lit(""))
    return F.struct(F.xxhash64(text).alias("h"), F.crc32(text).alias("c"), F.octet_length(text).alias("n"))


# ---- numpy on UTF-8 bytes -------------------------------------------------------------------


def mix(x: np.ndarray) -> np.ndarray:
    """64-bit finaliser (wraps around)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_BASE = np.uint64(0x9E3779B97F4A7C55)
_POWERS = np.ones(1, np.uint64)


def _powers(n: int) -> np.ndarray:
    global _POWERS
    if len(_POWERS) < n:
        p = np.full(1 << max(16, (n - 1).bit_length()), _BASE, np.uint64)
        p[0] = 1
        _POWERS = np.multiply.accumulate(p)
    return _POWERS[:n]


class Words:
    """Words of many texts: byte spans, owning text and 64-bit hashes, all flat.

    ``start``/``end`` index ``data``; words of text i are ``first[i]:first[i+1]``. Null texts have no words.
    """

    def __init__(self, texts: list[str | None]):
        raw = [(t or "").encode("utf-8", "surrogatepass") for t in texts]
        sizes = np.fromiter((len(r) + 1 for r in raw), np.int64, len(raw))
        self.data = np.frombuffer(b" ".join(raw) + b" ", np.uint8) if raw else np.zeros(0, np.uint8)
        self.offset = np.concatenate([[0], np.cumsum(sizes)])
        space = _SPACE[self.data]
        edge = np.flatnonzero(np.diff(np.concatenate([[True], space]).astype(np.int8)))
        self.start, self.end = edge[0::2], edge[1::2]
        self.first = np.searchsorted(self.start, self.offset)
        self._hash = None

    @property
    def hash(self) -> np.ndarray:
        if self._hash is None:
            self._hash = self.hash_of(self.start, self.end)
        return self._hash

    def hash_of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Hashes of the byte spans start:end; equal bytes have equal hashes."""
        n = len(self.data) + 1
        with np.errstate(over="ignore"):
            if getattr(self, "_sums", None) is None:
                self._sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum((self.data.astype(np.uint64) + np.uint64(1)) * _powers(n)[:-1], dtype=np.uint64)])
            value = (self._sums[end] - self._sums[start]) * _inverse_powers(n)[start]
            return mix(value ^ ((end - start).astype(np.uint64) << np.uint64(56)))

    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def owner(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), self.counts())

    def windows(self, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Hash, first word and owner of each run of k words within one text."""
        own = self.owner()
        n = len(own) - k + 1
        if n <= 0:
            return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        with np.errstate(over="ignore"):
            h = np.zeros(n, np.uint64)
            for j in range(k):
                h = h * np.uint64(0xD6E8FEB86659FD93) + self.hash[j : j + n]
            h = mix(h)
        at = np.flatnonzero(own[:n] == own[k - 1 :])
        return h[at], at, own[at]


_INVERSE = np.ones(1, np.uint64)


def _inverse_powers(n: int) -> np.ndarray:
    global _INVERSE
    if len(_INVERSE) < n:
        p = np.full(1 << max(16, (n - 1).bit_length()), np.uint64(pow(int(_BASE), -1, 1 << 64)), np.uint64)
        p[0] = 1
        _INVERSE = np.multiply.accumulate(p)
    return _INVERSE[:n]


def chunks(texts: list, limit: int = CHUNK_BYTES):
    """Slices of a list of texts of about ``limit`` characters; one longer text is a slice of its own."""
    at, held = 0, 0
    for i, t in enumerate(texts):
        n = len(t) if t else 0
        if i > at and held + n > limit:
            yield at, i
            at, held = i, 0
        held += n
    if at < len(texts):
        yield at, len(texts)


def whole_groups(batches, keys: list[str], rows: int = 8192, weight: str | None = None, most: int = 8 << 20):
    """Tables of whole runs of equal ``keys`` from batches sorted by them: about ``rows`` rows, or ``most`` bytes of the
    column ``weight``, unless one run is larger. Yields (table, first row of each run and the row count)."""
    import pyarrow as pa

    held: list = []
    n = size = 0

    def cut(table):
        same = np.ones(max(0, len(table) - 1), bool)
        for k in keys:
            v = np.asarray(table.column(k))
            same &= v[1:] == v[:-1]
        return np.concatenate([[0], np.flatnonzero(~same) + 1, [len(table)]]) if len(table) else np.zeros(1, np.int64)

    for batch in batches:
        held.append(batch)
        n += len(batch)
        size += batch.column(weight).nbytes if weight else 0
        if n >= rows or size >= most:
            table = pa.Table.from_batches(held)
            edges = cut(table)
            if len(edges) > 2:
                yield table.slice(0, edges[-2]).combine_chunks(), edges[:-1]
                rest = table.slice(edges[-2]).combine_chunks()
                held = rest.to_batches()
                n, size = len(rest), rest.column(weight).nbytes if weight else 0
    if n:
        table = pa.Table.from_batches(held).combine_chunks()
        yield table, cut(table)


def lists_of(column) -> tuple[np.ndarray, np.ndarray]:
    """Flat values and borders of a list column."""
    chunk = column.combine_chunks() if hasattr(column, "combine_chunks") else column
    return np.asarray(chunk.flatten()), np.concatenate([[0], np.cumsum(np.asarray(chunk.value_lengths()), dtype=np.int64)])
