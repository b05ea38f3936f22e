"""Byte-level BPE in numpy: batched merge rounds over the symbols of many words.

All words of a batch lie in one flat symbol array. A round finds each adjacent pair's rank by binary search in the
sorted pair keys, takes the lowest rank of every word and merges all places of that pair; words without a known pair
leave the array.

Cases: a null or empty text has no ids and decodes to the empty text; the special token's string in a text gives its id
(as the tokenizers library does); repeated rows give repeated results; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame

from .common import chunks

#: Fixed value: the public byte-level split pattern, white space spelt out.
_WS = r"\t-\r \x85\xa0  -     　"
SPLIT = regex.compile(rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{_WS}\p{{L}}\p{{N}}]+|[{_WS}]+(?![^{_WS}])|[{_WS}]+")
_NONE = np.int64(1) << 40
#: Words remembered by a Python worker between batches; beyond it the memory starts anew.
CACHE_WORDS = 200_000


def byte_letters() -> dict[int, str]:
    """The letter that stands for each byte in the vocabulary file."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {b: chr(b) for b in shown} | {b: chr(256 + i) for i, b in enumerate(hidden)}


class ByteBPE:
    """Encoder and decoder of one vocabulary file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab, merges = spec["model"]["vocab"], spec["model"]["merges"]
        letters = byte_letters()
        back = {c: b for b, c in letters.items()}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.token_bytes = {i: bytes(back[c] for c in t) for t, i in vocab.items()} | {i: t.encode() for t, i in self.special.items()}
        self.byte_id = np.array([vocab[letters[b]] for b in range(256)], np.int64)
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in merges]
        left, right = (np.array([vocab[p[k]] for p in pairs], np.int64) for k in (0, 1))
        made = np.array([vocab[a + b] for a, b in pairs], np.int64)
        key = (left << 32) | right
        order = np.argsort(key, kind="stable")
        self.keys, self.rank, self.made = key[order], order.astype(np.int64), made[order]
        self._special = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None
        self._known: dict[str, tuple[int, str, bytes]] = {}

    def merge(self, words: list[bytes]) -> list[np.ndarray]:
        """Ids of each word."""
        sizes = np.fromiter(map(len, words), np.int64, len(words))
        symbol = self.byte_id[np.frombuffer(b"".join(words), np.uint8)]
        word = np.repeat(np.arange(len(words)), sizes)
        place = np.arange(len(symbol))  # keeps the order of what leaves early
        done: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        while len(symbol):
            inside = word[1:] == word[:-1]
            key = (symbol[:-1] << 32) | symbol[1:]
            at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            rank = np.where(inside & (self.keys[at] == key), self.rank[at], _NONE)
            head = np.flatnonzero(np.concatenate([[True], word[1:] != word[:-1]]))
            lowest = np.minimum.reduceat(np.append(rank, _NONE), head)
            span = np.diff(np.append(head, len(word)))
            best = np.repeat(lowest, span)
            stuck = best == _NONE
            hit = np.flatnonzero((rank == best[:-1]) & ~stuck[:-1] & inside)
            if len(hit):  # of touching places of one pair (a a a) each second one stays
                run = np.concatenate([[True], np.diff(hit) != 1])
                hit = hit[(np.arange(len(hit)) - np.flatnonzero(run)[np.cumsum(run) - 1]) % 2 == 0]
                symbol[hit] = self.made[at[hit]]
            if stuck.any():
                done.append((word[stuck], place[stuck], symbol[stuck]))
            keep = ~stuck
            keep[hit + 1] = False
            symbol, word, place = symbol[keep], word[keep], place[keep]
        if not done:
            return [np.zeros(0, np.int64) for _ in words]
        word, place, symbol = (np.concatenate(x) for x in zip(*done, strict=True))
        order = np.argsort(place, kind="stable")
        return np.split(symbol[order], np.cumsum(np.bincount(word, minlength=len(words)))[:-1])

    def split(self, text: str) -> list[str]:
        """Pre-tokens; special tokens stand alone."""
        if not self._special or not any(s in text for s in self.special):
            return SPLIT.findall(text)
        out: list[str] = []
        for part in self._special.split(text):
            out.extend([part] if part in self.special else SPLIT.findall(part))
        return out

    def learn(self, words: set[str]) -> dict[str, tuple[int, str, bytes]]:
        """For each pre-token: number of ids, the ids in decimal joined by commas, the bytes that the ids decode to."""
        if len(self._known) > CACHE_WORDS:
            self._known = {}
        new = [w for w in words if w not in self._known]
        plain = [w for w in new if w not in self.special]
        for w, ids in zip(plain, self.merge([w.encode() for w in plain]), strict=True):
            ids = ids.tolist()
            self._known[w] = (len(ids), ",".join(map(str, ids)), b"".join(map(self.token_bytes.__getitem__, ids)))
        for w in new:
            if w in self.special:
                self._known[w] = (1, str(self.special[w]), w.encode())
        return self._known

    def encode(self, text: str) -> list[int]:
        words = self.split(text)
        known = self.learn(set(words))
        return [int(i) for w in words for i in known[w][1].split(",")]

    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.token_bytes.__getitem__, ids)).decode("utf-8", "replace")


@lru_cache(maxsize=2)
def encoder(path: str) -> ByteBPE:
    return ByteBPE(path)


def encode_documents(docs: DataFrame, path: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id and the ids of each whole text."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        bpe = encoder(path)
        for batch in batches:
            texts = batch["text"].tolist()
            for a, b in chunks(texts):
                yield pd.DataFrame({"doc_id": batch["doc_id"].iloc[a:b], "ids": [bpe.encode(t or "") for t in texts[a:b]]})

    return docs.selectExpr(f"cast(`{key}` as bigint) doc_id", f"`{text}` text").mapInPandas(run, "doc_id bigint, ids array<int>")


def decode_documents(encoded: DataFrame, path: str) -> DataFrame:
    """doc_id and the text of ``ids``; null ids decode to the empty text."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        bpe = encoder(path)
        for batch in batches:
            yield pd.DataFrame({"doc_id": batch["doc_id"], "text": [bpe.decode(list(x) if x is not None else []) for x in batch["ids"]]})

    return encoded.select("doc_id", "ids").mapInPandas(run, "doc_id bigint, text string")


def digests(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_tokens and SHA-256 of the ids and of the text decoded from them; no arrays leave the worker."""

    def run(batches):
        import pyarrow as pa

        bpe = encoder(path)
        for batch in batches:
            ids, texts = batch.column("doc_id"), batch.column("text").to_pylist()
            for a, b in chunks(texts, 1 << 20):
                split = [bpe.split(t) if t else [] for t in texts[a:b]]
                known = bpe.learn(set().union(*split))
                n, coded, decoded = [], [], []
                for words in split:
                    got = [known[w] for w in words]
                    n.append(sum(g[0] for g in got))
                    coded.append(hashlib.sha256(",".join([g[1] for g in got]).encode()).hexdigest())
                    decoded.append(hashlib.sha256(b"".join([g[2] for g in got]).decode("utf-8", "replace").encode()).hexdigest())
                yield pa.RecordBatch.from_arrays([ids.slice(a, b - a), pa.array(n, pa.int64()), pa.array(coded, pa.string()), pa.array(decoded, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.selectExpr("cast(doc_id as bigint) doc_id", "text").mapInArrow(run, "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string")


def op5_byte_bpe(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return digests(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("byte_bpe_50k.json"))
