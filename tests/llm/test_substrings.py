import hashlib
import random

import pytest

from foldstar.llm import substrings as S

SF = "/root/testdata/sf0.001"


def brute(rows, window=50):
    first = {}
    split = [[x for x in (t or "").translate({9: 32, 10: 32, 11: 32, 12: 32, 13: 32}).split(" ") if x] for _, t in rows]
    for (k, _), w in zip(rows, split):
        if k is not None:
            for i in range(len(w) - window + 1):
                g = tuple(w[i : i + window])
                first[g] = min(first.get(g, k), k)
    out = []
    for (k, _), w in zip(rows, split):
        gone = set()
        if k is not None:
            for i in range(len(w) - window + 1):
                if first[tuple(w[i : i + window])] < k:
                    gone.update(range(i, i + window))
        kept = [x for i, x in enumerate(w) if i not in gone]
        out.append((k, len(w), len(gone), hashlib.sha256(" ".join(kept).encode()).hexdigest()))
    return sorted(out, key=str)


def test_query(spark):
    rows = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{SF}/documents.parquet").collect()]
    got = sorted((tuple(r) for r in S.op8_substrings(spark, SF).collect()), key=str)
    assert got == brute(rows)


@pytest.mark.parametrize("salt", [4000, 2])
def test_planted(spark, monkeypatch, salt):
    monkeypatch.setattr(S, "SHARD_ROWS", salt)
    monkeypatch.setattr(S, "SHARD_WORDS", 120)
    r = random.Random(salt)
    word = lambda: "".join(r.choices("abcdeé", k=r.randint(1, 4)))
    pool = [[word() for _ in range(r.choice([49, 50, 51, 70, 120]))] for _ in range(6)]
    head = [word() for _ in range(30)]
    rows = []
    for i in range(60):
        w = list(head) if i % 2 else []
        for _ in range(r.randint(0, 4)):
            w += [word() for _ in range(r.randint(0, 30))] + r.choice(pool)
        rows.append((i * 3 % 61, r.choice([" ", "\n", "  "]).join(w)))
    rows += [(100, "a " * 500), (101, "b a " * 300), (102, "a " * 90), (103, None), (104, ""), (None, rows[3][1]), (100, "a " * 500), (100, rows[5][1])]
    df = spark.createDataFrame([(k, t, 5) for k, t in rows], "doc_id long, text string, at int")
    got = sorted((tuple(x) for x in S.summary(df).collect()), key=str)
    assert got == brute(rows)
    clean = S.cleaned(df)
    assert clean.columns == df.columns
    text = sorted((k, len((t or "").split()), hashlib.sha256(" ".join((t or "").split()).encode()).hexdigest()) for k, t, _ in map(tuple, clean.where("doc_id is not null").collect()))
    assert text == sorted((k, n - g, h) for k, n, g, h in got if k is not None)
    assert S.summary(df.limit(0)).count() == 0
