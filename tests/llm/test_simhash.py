import random

import numpy as np
import pandas as pd
import xxhash

from foldstar.llm import graph, simhash as S

SF = "/root/testdata/sf0.001"


def slow_print(t):
    w = [x for x in "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "").translate({9: 32, 10: 32, 11: 32, 12: 32, 13: 32}).split(" ") if x]
    if not w:
        return 0
    sh = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or [" ".join(w)]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in sh]
    return sum(1 << j for j in range(64) if 2 * sum(x >> j & 1 for x in h) > len(h))


def brute(keys, fps):
    up = {k: k for k in keys}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for i, a in enumerate(keys):
        for b in keys[:i]:
            if bin((fps[a] ^ fps[b]) & (2**64 - 1)).count("1") <= 3:
                x, y = root(a), root(b)
                up[max(x, y)] = min(x, y)
    return {k: root(k) for k in keys}


def test_query(spark):
    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    fps = {k: slow_print(t) for k, t in docs.items()}
    want = brute(sorted(docs), fps)
    got = {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in S.op6_simhash(spark, SF).collect()}
    assert got == {k: (f"{fps[k]:016x}", want[k]) for k in docs}


def test_spark_hash_agrees(spark):
    from pyspark.sql import functions as F

    assert spark.range(1).select(F.xxhash64(F.lit("ab cd éf"))).first()[0] & (2**64 - 1) == xxhash.xxh64_intdigest("ab cd éf".encode(), 42)


def test_dense_ball_with_small_groups(spark):
    r = random.Random(7)
    centre = r.getrandbits(64)
    fps = {}
    for i in range(300):
        x = centre if i % 3 else r.getrandbits(64)
        for _ in range(r.randint(0, 6)):
            x ^= 1 << r.randrange(64)
        fps[i] = x
    signed = [(i, x - (1 << 64) if x >> 63 else x) for i, x in fps.items()]
    df = spark.createDataFrame(signed, "i long, fp long").select("fp").distinct()
    want = brute(sorted(fps), fps)
    for limit in (2048, 4):
        root = {x["node"]: x["root"] for x in graph.components(S.links(df, group_limit=limit)).collect()}
        label = {i: root.get(s, s) for i, s in signed}
        same = {}
        for i in fps:
            same.setdefault(label[i], set()).add(want[i])
        assert all(len(v) == 1 for v in same.values())
        assert len(same) == len(set(want.values()))


def test_defined_cases(spark):
    texts = [None, "", " \n", "One two", "one TWO", "a b c d e " * 3000, "a b c d e " * 3000, "É é", "x"]
    df = spark.createDataFrame([(i, t, 1) for i, t in enumerate(texts)] + [(None, "one two", 2), (3, "One two", 3)], "doc_id long, text string, fp int")
    rows = [tuple(r) for r in S.near_duplicates(df).collect()]
    by = {k: (f & (2**64 - 1), c) for k, f, c in rows}
    for i, t in enumerate(texts):
        assert by[i][0] == slow_print(t)
    assert by[0][1] == by[1][1] == by[2][1] == 0 and by[4][1] == by[3][1] == by[None][1] == 3 and by[6][1] == 5
    kept = S.keep_first(df)
    assert kept.columns == df.columns
    assert sorted((r["doc_id"] is None, r["doc_id"] or 0) for r in kept.collect()) == [(False, 0), (False, 3), (False, 3), (False, 5), (False, 7), (False, 8), (True, 0)]
    assert S.near_duplicates(df.limit(0)).count() == 0


def test_groups_and_components(spark):
    f = pd.DataFrame({"c": [0, 0, 0, 1, 1, 2], "k": [1, 1, 2, 2, 2, 2], "v": range(6)})
    for size in (1, 2, 3, 6):
        got = [tuple(g["v"]) for g in graph.groups([f.iloc[i : i + size] for i in range(0, 6, size)], ["c", "k"])]
        assert got == [(0, 1), (2,), (3, 4), (5,)]
    chain = [(i, i + 1) for i in range(0, 40)] + [(100, 101), (5, 5), (None, 3)] + [(200, 200 + i) for i in range(1, 60)]
    got = {r["node"]: r["root"] for r in graph.components(spark.createDataFrame(chain, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 101: 100, **{200 + i: 200 for i in range(60)}}
    forest = graph.Forest(6)
    forest.add(np.array([5, 3]), np.array([4, 4]))
    assert forest.up.tolist() == [0, 1, 2, 3, 3, 3]
