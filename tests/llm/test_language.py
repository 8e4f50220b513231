import zlib

import numpy as np

from foldstar.llm import language as L

SF = "/root/testdata/sf0.01"


def test_held_out_accuracy(spark):
    lang = {r["doc_id"]: r["lang"] for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    rows = L.op2_language(spark, SF).collect()
    assert len(rows) == len(lang)
    for r in rows:
        assert r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2)
        assert 0 <= r["score"] <= 1
    held = [r for r in rows if r["held_out"]]
    good = sum(r["lang_pred"] == lang[r["doc_id"]] for r in held) / len(held)
    assert good > 0.97, good
    # calibration: mean score is near the accuracy
    assert abs(np.mean([r["score"] for r in held]) - good) < 0.05


def test_counts_in_pieces(monkeypatch):
    t = "Añb cd" * 50
    whole = L.gram_counts(t)
    monkeypatch.setattr(L, "_PIECE", 7)
    assert (L.gram_counts(t) == whole).all() and whole.sum() == 300 + 299 + 298


def test_penalty_makes_zeros_and_labels_order():
    g = np.random.default_rng(0)
    rows = []
    for j in range(200):
        y = j % 2
        c = {"i": [y, 2 + int(g.integers(20))], "n": [3, 1]}
        rows.append({"_y": "ba"[y], "c": c})
    df = np.full(64, 20)
    m = L.train(rows, 200, df, l1=1.0)
    assert m.labels == ["a", "b"] and m.zero_share > L.train(rows, 200, df, l1=0.0).zero_share
    counts = np.zeros(64, dtype=int)
    counts[0] = 3
    assert m.labels[int(m.scores(counts).argmax())] == "b"


def test_defined_cases(spark):
    texts = [None, "", "123 !!", "der die das und", "the and of", "x " * 50000, "É"]
    rows = [(i, t, ["de", "en", None][i % 3], 0.5) for i, t in enumerate(texts * 4)] + [(None, "the", "en", 0.1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, score double")
    got = {r["doc_id"]: r for r in L.predict(df, L.learn_model(df)).collect()}
    assert len(got) == len(rows) and got[None]["held_out"] is False
    for i, t in enumerate(texts):
        assert (got[i]["lang_pred"] == "und") == (i < 3)
    bare = df.where("lang is null")
    assert {r["score"] for r in L.predict(bare, L.learn_model(bare)).collect()} <= {0.0, 1.0}
    assert L.predict(df.limit(0), L.learn_model(df.limit(0))).count() == 0
