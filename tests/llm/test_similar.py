import random

import corpus_pipeline as C
from foldstar.llm import simhash
from foldstar.llm import similar as S


def brute(docs, t=0.8, k=5):
    """Smallest key of each component of pairs with Jaccard >= t, all pairs tried."""
    sets = {i: {tuple(w[j : j + k]) for j in range(max(1, len(w) - k + 1))} for i, x in docs.items() for w in [(x or "").lower().split()]}
    root = {i: i for i in docs}
    for a in sorted(docs):
        for b in sorted(docs):
            if a < b and len(sets[a] & sets[b]) >= t * len(sets[a] | sets[b]):
                x, y = sorted((root[a], root[b]))
                root = {i: x if r == y else r for i, r in root.items()}
    return root


def some(r):
    docs = {}
    for g in range(12):
        w = [f"w{r.randrange(500)}" for _ in range(r.randint(3, 120))]
        for _ in range(4):
            v = list(w)
            for _ in range(r.randint(0, 3)):
                v[r.randrange(len(v))] = f"x{r.randrange(500)}"
            docs[len(docs)] = " ".join(v)
    return docs | {200: "", 201: None, 202: "One two", 203: "one TWO"}


def test_all_pairs_found(spark):
    docs = some(random.Random(5))
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    want = brute(docs)
    for group in (1, 64):
        assert {r["_k"]: r["component_id"] for r in S.near_duplicates(df, group=group).collect()} == want
    assert {r["doc_id"] for r in S.keep_first(df).collect()} == {k for k in want if want[k] == k} != set(want)


def near_copies(r, copies):
    """Copies of one text with a passage of their own, so that only the first text is like each of them, and texts that hold half of it."""
    base = [f"w{i}" for i in range(100)]
    docs = {1000: " ".join(base)}
    for g in range(copies):
        v = list(base)
        at = r.randrange(0, 90)
        v[at : at + 5] = [f"x{g}y{j}" for j in range(5)]
        docs[g] = " ".join(v)
    for g in range(copies):
        docs[2000 + g] = " ".join(base[:55] + [f"z{g}y{j}" for j in range(45)])
    return docs


def test_large_group_is_linked_without_all_pairs(spark, monkeypatch):
    docs = near_copies(random.Random(3), 60)
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    tried, plain = [], S.verified

    def counted(pairs, nodes, threshold):
        tried.append(pairs.distinct().count())
        return plain(pairs, nodes, threshold)

    monkeypatch.setattr(S, "verified", counted)
    assert {r["_k"]: r["component_id"] for r in S.near_duplicates(df, group=8).collect()} == brute(docs)
    assert sum(tried) < 60 * 59 / 4


def test_columns_and_odd_rows(spark):
    df = spark.createDataFrame([(1, None, "p"), (None, "a b", "q"), (2, "", "r"), (3, "a b", "s"), (3, "a b", "s")], "doc_id long, text string, node string")
    got = sorted(((r["doc_id"] or 0), r["node"]) for r in S.keep_first(df).collect())
    assert got == [(0, "q"), (1, "p"), (3, "s"), (3, "s")]
    assert S.keep_first(df.limit(0)).collect() == []


def test_stage_drops_what_three_bits_keep(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    root = brute(texts)
    kept = {r["doc_id"] for r in dict(C.STAGES)["near-dedup"](spark, docs, "").collect()}
    assert kept == {k for k in texts if root[k] == k}
    assert {r["doc_id"] for r in simhash.keep_first(docs).collect()} - kept
