import random
import zlib

import numpy as np
import public_tokenizers as P
from tokenizers import Tokenizer

from foldstar.llm import packing as K

SF = "/root/testdata/sf0.001"
TOK = Tokenizer.from_file(P.path("byte_bpe_50k.json"))


def ids_of(t):
    return np.array([*TOK.encode(t or "", add_special_tokens=False).ids, 2], dtype="<u4")


def check(rows, docs, size=1024):
    """Every piece is as the library's ids say; sequences are gapless and not too long. Returns their number."""
    by_doc, by_seq = {}, {}
    for d, piece, start, length, crc, seq, off in rows:
        by_doc.setdefault(d, []).append((piece, start, length, crc))
        by_seq.setdefault(seq, []).append((off, length))
    assert by_doc.keys() == docs.keys()
    for d, got in by_doc.items():
        got.sort()
        ids = ids_of(docs[d])
        assert [p for p, *_ in got] == list(range(len(got)))
        at = 0
        for i, (_, start, length, crc) in enumerate(got):
            assert start == at and 0 < length <= size and (i == 0 or length == size)
            assert crc == zlib.crc32(ids[at : at + length].tobytes())
            at += length
        assert at == len(ids) and (len(ids) > size or len(got) == 1)
    for held in by_seq.values():
        at = 0
        for off, length in sorted(held):
            assert off == at
            at += length
        assert at <= size
    return len(by_seq)


def test_query(spark):
    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    rows = [(r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"], r["sequence_id"], r["offset"]) for r in K.op7_packing(spark, SF).collect()]
    n = check(rows, docs)
    assert n <= 1.02 * -(-sum(len(ids_of(t)) for t in docs.values()) // 1024) + 1


def test_defined_cases(spark, monkeypatch):
    monkeypatch.setattr(K, "BUCKET_ROWS", 3)
    docs = {0: None, 1: "", 2: "hello", 3: "x y " * 3000, 4: "a<|endoftext|>b", 5: "日本 𝄞 é", 6: "same", 7: "same"}
    df = spark.createDataFrame([(k, t, 1) for k, t in docs.items()], "doc_id long, text string, piece int")
    rows = [(r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"], r["sequence_id"], r["offset"]) for r in K.packed_text(df).collect()]
    check(rows, docs)
    assert K.packed_text(df.limit(0)).count() == 0
    doubled = K.packed_text(df.union(df)).collect()
    assert len(doubled) == 2 * len(rows) and len({(r["sequence_id"], r["offset"]) for r in doubled}) == len(doubled)


def test_fast_ids_equal_library():
    fast = K.Ids(P.path("byte_bpe_50k.json"), P.path("byte_bpe_50k.tiktoken"), P.PATTERN)
    r = random.Random(2)
    parts = ["a", "The", " ", "  ", "\n", "\t", "\r", "é", "ß", "'s", "'S", "12", "½", "²", "ª", "\xa0", "\xad", "<|endoftext|>", "<|", "!!", "–", "…", "€", "日", "\x85", "\x1c", "x" * 40]
    for _ in range(4000):
        t = "".join(r.choices(parts, k=r.randint(0, 25)))
        assert fast(t).tolist() == TOK.encode(t, add_special_tokens=False).ids, t


def test_plan_covers_histogram():
    r = random.Random(4)
    for size, n in ((16, 40), (64, 500), (256, 5000)):
        hist = {}
        for _ in range(n):
            k = min(size, max(1, int(r.expovariate(3 / size))))
            hist[k] = hist.get(k, 0) + 1
        out = K.plan(hist, size)
        held = {}
        for lengths, k in out:
            assert sum(lengths) <= size and k > 0
            for x in lengths:
                held[x] = held.get(x, 0) + k
        assert held == hist
        need = -(-sum(a * b for a, b in hist.items()) // size)
        assert sum(k for _, k in out) <= max(need + 1, 1.01 * need)
    assert K.plan({}) == []
