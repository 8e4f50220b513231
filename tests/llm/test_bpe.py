import hashlib
import random

import public_tokenizers as P
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st

from foldstar.llm import bpe

PATH = P.path("byte_bpe_multi_50k.tiktoken")


@pytest.fixture(scope="module")
def pair():
    b = bpe.loaded(PATH, P.PATTERN)
    return b, tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=b.ranks, special_tokens={})


def expected(enc, t):
    ids = enc.encode_ordinary(t)
    return len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(enc.decode_bytes(ids)).hexdigest()


@settings(max_examples=300, deadline=None)
@given(t=st.text(st.characters(exclude_categories=["Cs"]), min_size=1) | st.text(" \n\taé's1!", min_size=1))
def test_equals_library(pair, t):
    b, enc = pair
    assert b.encode(t) == enc.encode_ordinary(t)
    assert b.digest(t) == expected(enc, t)
    assert b.decode(b.encode(t)) == t.encode()


def test_long_pre_tokens(pair):
    b, enc = pair
    r = random.Random(3)
    for t in ("a" * 30_000, "".join(r.choices("abcde", k=30_000)), "".join(r.choices("ab", k=30_000))):
        assert b.encode(t) == enc.encode_ordinary(t)


def test_frames(spark, pair):
    b, enc = pair
    texts = [None, "", "hello  world\n", "<|endoftext|>", "x " * 5000, "same", "same"]
    df = spark.createDataFrame([(i, t, "z") for i, t in enumerate(texts)], "doc_id long, text string, n_tokens string")
    got = {r["doc_id"]: tuple(r)[1:] for r in bpe.round_trip(df, PATH, P.PATTERN).collect()}
    for i, t in enumerate(texts):
        assert got[i] == (expected(enc, t) if t else (0, hashlib.sha256(b"").hexdigest(), hashlib.sha256(b"").hexdigest()))
    back = {r["doc_id"]: r["text"] for r in bpe.decoded(bpe.encoded(df, PATH, P.PATTERN), PATH, P.PATTERN).collect()}
    assert back == {i: t or "" for i, t in enumerate(texts)}
    assert bpe.round_trip(df.limit(0), PATH, P.PATTERN).count() == 0


def test_query(spark, pair):
    sf = "/root/testdata/sf0.001"
    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    got = {r["doc_id"]: tuple(r)[1:] for r in bpe.op9_byte_bpe(spark, sf).collect()}
    assert got == {k: expected(pair[1], t) for k, t in docs.items()}
