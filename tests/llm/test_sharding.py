"""Shards: the law of growth, gapless slots, sizes and checksums."""

import zlib
from collections import Counter

import numpy as np

from partgraph.llm import sharding as S


def jump(key, shards):
    b, j = -1, 0
    key &= (1 << 64) - 1
    while j < shards:
        b = j
        key = (key * 2862933555777941757 + 1) % (1 << 64)
        j = int((b + 1) * (float(1 << 31) / ((key >> 33) + 1)))
    return b


def test_jump_hash_equals_the_loop_and_moves_little():
    keys = np.array([*range(-50, 500), 2**62, -(2**62)], np.int64)
    for n in (1, 2, 24, 25):
        assert S.jump_hash(keys, n).tolist() == [jump(int(k), n) for k in keys]
    a, b = S.jump_hash(np.arange(20_000), 24), S.jump_hash(np.arange(20_000), 25)
    assert set(b[a != b]) == {24} and abs((a != b).mean() - 1 / 25) < 0.01


def test_rows(spark):
    rows = [(i, f"text é {i % 9}", 1, "x") for i in range(500)] + [(None, None, 1, "x"), (7, "text é 7", 1, "x"), (7, "text é 7", 1, "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, shard int, law string")
    got = S.shard(df, 24).collect()
    assert len(got) == len(rows)
    assert sorted((r.doc_id or -1, r["size"], r.text_crc32) for r in got) == sorted((d or -1, len((t or "").encode()) + 8, zlib.crc32((t or "").encode())) for d, t, _, _ in rows)
    for r in got:
        assert r.law == "key" and r["shard"] == jump(r.doc_id or 0, 24) and r.grown_shard in (r["shard"], 24)
    for s, n in Counter(r["shard"] for r in got).items():
        assert sorted(r.slot for r in got if r["shard"] == s) == list(range(n))
    assert S.shard(df.limit(0), 24).count() == 0


def test_written_shards(spark, tmp_path):
    df = spark.createDataFrame([(i, f"t{i}") for i in range(100)], "doc_id long, text string")
    S.write_shards(df, str(tmp_path / "s"), 5)
    back = spark.read.parquet(str(tmp_path / "s")).collect()
    assert sorted(r.doc_id for r in back) == list(range(100)) and all(r["shard"] == jump(r.doc_id, 5) for r in back)
