"""Encoding against the tokenizers library, and the round trip."""

import hashlib
import random

import public_tokenizers
from tokenizers import Tokenizer

from partgraph.llm import bpe as B

PATH = public_tokenizers.path("byte_bpe_50k.json")


def texts():
    rnd = random.Random(1)
    letters = "abc dE  \n\t'sre’ éß漢字😀 ‍0123,.!?#<|endoftext|>"
    made = ["".join(rnd.choice(letters) for _ in range(rnd.randint(0, 80))) for _ in range(300)]
    return [*made, None, "", " ", "a" * 5000, "\x00\x1f", "word " * 2000, "<|endoftext|>", "don't we'LL"]


def test_digests_equal_the_library(spark):
    rows = list(enumerate(texts())) + [(None, "x"), (3, "x"), (3, "x")]
    df = spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, n_tokens int")
    tok = Tokenizer.from_file(PATH)
    tok.no_truncation()
    tok.no_padding()
    want = []
    for d, t in rows:
        ids = tok.encode(t or "", add_special_tokens=False).ids
        want.append((d or -1, len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(tok.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    got = [(r.doc_id or -1, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in B.digests(df, PATH).collect()]
    assert sorted(got) == sorted(want)
    assert B.digests(df.limit(0), PATH).count() == 0


def test_round_trip(spark):
    rows = [(i, t) for i, t in enumerate(texts()) if t is not None]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    back = {r.doc_id: r.text for r in B.decode_documents(B.encode_documents(df, PATH), PATH).collect()}
    assert back == dict(rows)
