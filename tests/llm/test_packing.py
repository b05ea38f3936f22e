"""Packing: every token once, gapless sequences, and what the genetic step gains over best fit."""

import random
import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pyarrow.compute as pc
from tokenizers import Tokenizer

from partgraph.llm import packing as P

PATH = public_tokenizers.path("byte_bpe_50k.json")


def test_pieces_and_sequences(spark):
    rnd = random.Random(4)
    rows = [(i, " ".join(rnd.choice(["stone", "river", "été", "light"]) for _ in range(rnd.randint(0, 1500)))) for i in range(60)]
    rows += [(900, None), (901, ""), (902, "word " * 9000), (None, "same"), (None, "same"), (5, rows[5][1])]
    df = spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, start int")
    got = P.pack_documents(df, PATH).collect()
    tok = Tokenizer.from_file(PATH)
    tok.no_truncation()
    want = []
    for d, t in rows:
        ids = [*tok.encode(t or "", add_special_tokens=False).ids, 0]
        first = len(ids) % 2048 or 2048
        cuts = [0, *range(first, len(ids) + 1, 2048)]
        for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
            want.append((-1 if d is None else d, k, a, b - a, zlib.crc32(np.array(ids[a:b], "<u4").tobytes())))
    assert sorted((-1 if r.doc_id is None else r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in got) == sorted(want)
    bins = {}
    for r in got:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for b in bins.values():
        at = 0
        for offset, length in sorted(b):
            assert offset == at
            at += length
        assert at <= 2048
    assert len(bins) <= -(-sum(x[3] for x in want) // 2048) + 1
    assert P.pack_documents(df.limit(0), PATH).count() == 0


def hard_sizes(n=60, seed=3):
    """Triples that fill a bin exactly, which best fit does not find."""
    rnd = random.Random(seed)
    out = []
    for _ in range(n):
        a, b = rnd.randint(500, 800), rnd.randint(500, 800)
        out += [a, b, 2048 - a - b]
    rnd.shuffle(out)
    return out


def test_islands_gain_over_best_fit(spark, monkeypatch):
    monkeypatch.setattr(P, "GENERATIONS", 60)
    size = hard_sizes()
    start = len(P.best_fit(list(range(len(size))), size, 2048))
    goal = P.lower_bound(size, 2048)
    assert start > goal
    dealt = spark.createDataFrame([(i, 0, 0, s, 0, i) for i, s in enumerate(size)], "doc_id long, piece int, start long, length long, ids_crc32 long, deal long")
    got = P.pack_pieces(dealt, len(size)).collect()
    assert goal <= len({r.sequence_id for r in got}) < start and len(got) == len(size)


def test_operators_of_the_algorithm_keep_every_piece():
    size = hard_sizes(20)
    rng = random.Random(1)
    a, b = P.founders(size, 2048, 1)[:2]
    for child in (P.cross(a, b, size, 2048, rng), P.mutate(a, size, 2048, rng), P.breed([a, b, a, b], size, 2048, 0, 1)[0]):
        assert sorted(x for g in child for x in g) == list(range(len(size)))
        assert all(sum(size[x] for x in g) <= 2048 for g in child)


def test_loose_bins_are_merged_across_groups(spark, monkeypatch):
    monkeypatch.setattr(P, "GROUP", 10)
    rows = [(i, 0, 0, 300, 0, i) for i in range(80)]
    dealt = spark.createDataFrame(rows, "doc_id long, piece int, start long, length long, ids_crc32 long, deal long")
    got = P.pack_pieces(dealt, 80).collect()
    bins = {}
    for r in got:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert all(sorted(o for o, _ in b) == [300 * k for k in range(len(b))] for b in bins.values()) and sum(map(len, bins.values())) == 80


def test_each_grouping_is_scored_once(monkeypatch):
    size = hard_sizes(20)
    seen = []
    monkeypatch.setattr(P, "_fitness", lambda b, s, c, f=P._fitness: seen.append(1) or f(b, s, c))
    P.breed(P.founders(size, 2048, 1), size, 2048, 0, 1)
    assert len(seen) == P.POPULATION + P.GENERATIONS


def fewest(size, capacity):
    """Bins of a best grouping, by trying all."""
    best = [len(size)]

    def put(i, rooms):
        if len(rooms) >= best[0]:
            return
        if i == len(size):
            best[0] = len(rooms)
            return
        for k, room in enumerate(rooms):
            if room >= size[i] and room not in rooms[:k]:
                put(i + 1, [*rooms[:k], room - size[i], *rooms[k + 1 :]])
        put(i + 1, [*rooms, capacity - size[i]])

    put(0, [])
    return best[0]


def test_settled_bins_cost_no_bin():
    rnd = random.Random(8)
    met = 0
    for _ in range(150):
        size = [rnd.randint(1, 12) for _ in range(9)]
        fixed, free = P.settle(P.best_fit(list(range(9)), size, 12), size, 12)
        assert sorted(x for b in fixed + free for x in b) == list(range(9))
        assert fewest(size, 12) == len(fixed) + fewest([size[x] for b in free for x in b], 12)
        met += bool(fixed)
    assert met > 50


def test_islands_carry_no_settled_bins(spark, monkeypatch):
    monkeypatch.setattr(P, "GENERATIONS", 60)
    hard = hard_sizes()
    size = hard + [2048] * 50 + [1900, 148] * 40
    start = len(P.best_fit(list(range(len(size))), size, 2048))
    dealt = spark.createDataFrame([(i, 0, 0, s, i, i) for i, s in enumerate(size)], "doc_id long, piece int, start long, length long, ids_crc32 long, deal long")
    first = P.islands_of(dealt.selectExpr("*", "0L grp"), 2048).first()
    assert first.bins == start > first.goal
    assert len(first.size) <= len(hard) and len(first.size) == len(size) - sum(n < first.settled for n in first.numbers)
    assert [r.length for r in first.rows][-len(first.size) :] == first.size
    got = P.pack_pieces(dealt, len(size)).collect()
    assert sorted((r.doc_id, r.length, r.ids_crc32) for r in got) == [(i, s, i) for i, s in enumerate(size)]
    bins = {}
    for r in got:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for b in bins.values():
        b.sort()
        assert all(o == sum(n for _, n in b[:k]) for k, (o, _) in enumerate(b)) and sum(n for _, n in b) <= 2048
    assert first.goal <= len(bins) < start


def test_split_without_looking_ahead_gives_the_same_ids():
    assert P.AHEAD in P.SPLIT.pattern and "(?!" not in P.PLAIN
    tok = Tokenizer.from_file(PATH)
    tok.no_truncation()
    special = sorted(P.fast_encoder(PATH).special_tokens_set)
    atoms = [" ", "  ", "\n", "\n\n", "\t", "\r\n", "\x85", "\xa0", " ", "　", "​", "\x1c", "a", "été", "Zoo", "'s", "'ll", "12", "!?", "漢字", "😀", *special]
    encode, rnd, met = P.encoder(PATH), random.Random(5), 0
    for _ in range(3000):
        text = "".join(rnd.choice(atoms) for _ in range(rnd.randint(1, 14)))
        runs = pc.match_substring_regex(pa.array([text]), P.RUN)[0].as_py()
        assert encode(text, runs).tolist() == tok.encode(text, add_special_tokens=False).ids, text
        met += runs
    assert 500 < met < 2500


def test_pairs_of_loose_pieces_are_found_by_their_sums():
    rnd = random.Random(9)
    for _ in range(200):
        have = sorted((rnd.randint(1, 40), i) for i in range(rnd.randint(1, 40)))
        most, limit = P.TRADED + 1, rnd.randint(2, 90)
        fit = [n for n in P._pair_sums(have, most) if n // most**2 <= limit]
        sums = [have[i][0] + have[j][0] for j in range(min(most, len(have))) for i in range(j)]
        assert len(fit) == sum(s <= limit for s in sums)
        if fit:
            low, high = most - 1 - fit[-1] // most % most, fit[-1] % most
            assert low < high and have[low][0] + have[high][0] == fit[-1] // most**2 == max(s for s in sums if s <= limit)
