import random

import public_tokenizers as P
from tokenizers import Tokenizer

from foldstar.llm import token_counts as C

PATH = P.path("word_bpe_49k.json")
SF = "/root/testdata/sf0.001"


def lib(t):
    return len(Tokenizer.from_file(PATH).encode(t, add_special_tokens=False).ids) if t else 0


def test_query(spark):
    tok = Tokenizer.from_file(PATH)
    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    for r in C.op1_token_counts(spark, SF).collect():
        n = len(tok.encode(docs[r["doc_id"]], add_special_tokens=False).ids)
        assert (r["n_bytes"], r["n_tokens"], r["over_limit"]) == (len(docs[r["doc_id"]].encode()), n, n > 2048)


def test_pieces_equal_library():
    tok = Tokenizer.from_file(PATH)
    r = random.Random(5)
    parts = ["a", "The", " ", "  ", "\n", "\t", "é", "É", "é", "́", "'s", "12", "<|endoftext|>", "<|ENDOFTEXT|>", "<|end", "oftext|>", "!!", "　", "\xa0", "\x85", "\x1c", "ß", "Σ", "İ", "日本", "🙂", "x" * 40]
    texts = ["".join(r.choices(parts, k=r.randint(0, 25))) for _ in range(4000)]
    assert C.PieceCounter(PATH).counts(texts) == [len(tok.encode(t, add_special_tokens=False).ids) for t in texts]


def test_defined_cases_and_cache(spark, tmp_path):
    texts = [None, "", "Hello  World", "hello world", "hello\nworld ", "É", "<|endoftext|> x", "y " * 4000, "hello world"]
    rows = [(i, t, "clash") for i, t in enumerate(texts)] + [(None, "no key", "c"), (None, "hello world", "c"), (2, "Hello  World", "c")]
    df = spark.createDataFrame(rows, "doc_id long, text string, digest string")
    cache = str(tmp_path / "cache")
    got = sorted(map(tuple, C.count_tokens(df, PATH, cache).collect()), key=str)
    assert got == sorted(((k, len((t or "").encode()), lib(t)) for k, t, _ in rows), key=str)
    kept = spark.read.parquet(cache)
    n = kept.count()
    assert n == kept.select("digest").distinct().count() == 6
    assert sorted(map(tuple, C.count_tokens(df, PATH, cache).collect()), key=str) == got
    assert spark.read.parquet(cache).count() == n
    C.count_tokens(spark.createDataFrame([(1, "fresh")], "doc_id long, text string"), PATH, cache).collect()
    assert spark.read.parquet(cache).count() == n + 1
    assert C.count_tokens(df.limit(0), PATH).count() == 0


def test_other_tokenizers_get_whole_texts(spark):
    """A tokenizer that keeps case and white space may not share counts across them."""
    path = P.path("byte_bpe_50k.json")
    assert C.drops_space(PATH) and not C.drops_space(path)
    tok = Tokenizer.from_file(path)
    texts = ["Hello  World", "hello world", "hello\nworld ", "a  b", "A b", None, ""]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r["n_tokens"] for r in C.count_tokens(df, path).collect()}
    assert got == {i: len(tok.encode(t or "", add_special_tokens=False).ids) for i, t in enumerate(texts)}
