"""FM-index over words in numpy: bit-packed wavelet matrix of the BWT, batched backward search."""

from __future__ import annotations

import numpy as np


def suffix_order(symbols: np.ndarray, depth: int) -> np.ndarray:
    """Suffixes sorted by their first ``depth`` symbols at least (enough for patterns up to that length)."""
    n = len(symbols)
    rank = symbols.astype(np.uint64)
    have = 1
    while True:
        wide = int(rank.max()) + 2 if n else 2
        take = 3 if wide < (1 << 21) else 2
        key = np.zeros(n, np.uint64)
        for j in range(take):
            shifted = np.zeros(n, np.uint64)
            if j * have < n:
                shifted[: n - j * have] = rank[j * have :] + np.uint64(1)
            key = key * np.uint64(wide) + shifted
        order = np.argsort(key)
        have *= take
        if have >= depth:
            return order
        sorted_key = key[order]
        rank = np.empty(n, np.uint64)
        rank[order] = np.cumsum(np.concatenate([[0], sorted_key[1:] != sorted_key[:-1]])).astype(np.uint64)
        if n == 0 or int(rank.max()) == n - 1:
            return order


class FMIndex:
    """Counts of patterns in a sequence of small integers (0 .. sigma - 1)."""

    def __init__(self, symbols: np.ndarray, depth: int):
        order = suffix_order(symbols, depth)
        bwt = symbols[order - 1].astype(np.int64)  # the suffix at 0 takes the last symbol
        self.n = len(symbols)
        sigma = int(symbols.max()) + 1 if self.n else 1
        self.first = np.concatenate([[0], np.cumsum(np.bincount(symbols, minlength=sigma))]).astype(np.int64)
        self.levels: list[tuple[int, np.ndarray, np.ndarray, int]] = []
        for shift in range(max(1, (sigma - 1).bit_length()) - 1, -1, -1):
            bit = ((bwt >> shift) & 1).astype(np.uint8)
            packed = np.packbits(bit, bitorder="little")
            words = np.zeros((len(bit) >> 6) + 1, np.uint64)
            words.view(np.uint8)[: len(packed)] = packed
            counts = np.concatenate([[0], np.cumsum(np.bitwise_count(words), dtype=np.int64)])[:-1]
            zeros = int(len(bit) - bit.sum())
            self.levels.append((shift, words, counts, zeros))
            bwt = np.concatenate([bwt[bit == 0], bwt[bit == 1]])
        every = np.arange(sigma)
        self.origin = self._down(every, np.zeros(sigma, np.int64))

    def _down(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Place of each prefix end ``at`` below the wavelet path of ``symbol``."""
        for shift, words, counts, zeros in self.levels:
            cell = at >> 6
            inside = np.bitwise_count(words[cell] & ((np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)))
            ones = counts[cell] + inside
            at = np.where((symbol >> shift) & 1, zeros + ones, at - ones)
        return at

    def extend(self, symbol: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """One backward step for many patterns: the intervals of symbol + pattern."""
        both = self._down(np.concatenate([symbol, symbol]), np.concatenate([low, high]))
        base = self.first[symbol] - self.origin[symbol]
        k = len(symbol)
        return base + both[:k], base + both[k:]


def repeated_spans(index: FMIndex, symbols: np.ndarray, start: np.ndarray, words: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """(segment, window start) of windows that occur twice or more in the index and cover all such windows' words.

    Segment i is ``symbols[start[i] : start[i] + words[i]]``. A window is searched from its last word back. When the
    search fails at word p, each window that holds p .. end is skipped. After a hit the farthest window that still
    touches it is tried, then nearer ones, so that a run of hits costs one search for each ``window`` words.
    """
    k = len(start)
    last = words - window  # last window start
    low, high = np.zeros(k, np.int64), np.full(k, index.n, np.int64)
    t = np.zeros(k, np.int64)  # window tried
    p = np.full(k, window - 1, np.int64)  # next word to take
    hit = np.full(k, -1, np.int64)  # last hit that is being extended, or -1
    resume = np.zeros(k, np.int64)  # where scanning goes on after the extension
    fresh = np.ones(k, bool)  # first failure of an extension sets resume
    live = np.flatnonzero(last >= 0)
    out: list[tuple[np.ndarray, np.ndarray]] = []
    while len(live):
        lo, hi = index.extend(symbols[start[live] + p[live]], low[live], high[live])
        good = hi - lo >= 2
        low[live], high[live] = lo, hi
        ended = good & (p[live] == t[live])
        p[live[good & ~ended]] -= 1
        failed = ~good
        new: list[np.ndarray] = []
        if ended.any():
            who = live[ended]
            out.append((who, t[who].copy()))
            hit[who], fresh[who] = t[who], True
            resume[who] = t[who] + 1
            t[who] = np.minimum(t[who] + window, last[who])
            new.append(who)
        if failed.any():
            who = live[failed]
            ext = hit[who] >= 0
            plain, more = who[~ext], who[ext]
            t[plain] = p[plain] + 1
            first = more[fresh[more]]
            resume[first], fresh[first] = p[first] + 1, False
            t[more] -= 1
            back = more[t[more] <= hit[more]]
            t[back], hit[back] = resume[back], -1
            new.append(who)
        done = np.zeros(k, bool)
        for who in new:
            over = who[(t[who] > last[who]) | ((hit[who] >= 0) & (t[who] <= hit[who]))]
            done[over] = True
            p[who] = t[who] + window - 1
            low[who], high[who] = 0, index.n
        live = live[~done[live]]
    if not out:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate([o[0] for o in out]), np.concatenate([o[1] for o in out])
