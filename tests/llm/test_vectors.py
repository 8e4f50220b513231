import math
import random

import numpy as np

from foldstar.llm import vectors as V

SF = "/root/testdata/sf0.001"


def brute(rows, cosine=0.95):
    ok = [i for i, (k, v) in enumerate(rows) if k is not None and v and all(x is not None and math.isfinite(x) for x in v) and any(v)]
    links = [0] * len(rows)
    up = list(range(len(rows)))

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for x, i in enumerate(ok):
        for j in ok[:x]:
            a, b = np.array(rows[i][1], float), np.array(rows[j][1], float)
            if len(a) == len(b) and a @ b / (np.linalg.norm(a) * np.linalg.norm(b)) >= cosine:
                links[i] += 1
                links[j] += 1
                up[root(i)] = root(j)
    low = {}
    for i in ok:
        r = root(i)
        low[r] = min(low.get(r, rows[i][0]), rows[i][0])
    return sorted(((k, links[i], low[root(i)] if i in ok else k) for i, (k, _) in enumerate(rows)), key=str)


def test_query(spark):
    rows = [(r["vec_id"], list(r["embedding"])) for r in spark.read.parquet(f"{SF}/embeddings.parquet").collect()]
    got = V.op3_vectors(spark, SF).collect()
    assert sorted(((r["vec_id"], r["n_links"], r["component_id"]) for r in got), key=str) == brute(rows)
    assert all(r["kept"] == (r["vec_id"] == r["component_id"]) for r in got)


def test_planted_in_small_blocks(spark, monkeypatch):
    monkeypatch.setattr(V, "BLOCK_ROWS", 16)
    monkeypatch.setattr(V, "LEAF", 4)
    monkeypatch.setattr(V, "TILE_BLOCKS", 2)
    g = np.random.default_rng(6)
    rows = []
    for c in range(12):
        centre = g.normal(size=8)
        for _ in range(g.integers(1, 15)):
            rows.append((len(rows) * 7 % 1009, (centre + g.normal(size=8) * g.choice([0.05, 0.2, 0.4])).astype(np.float32).tolist()))
    rows += [(2000 + i, rows[3][1]) for i in range(20)]
    rows += [(3000, None), (3001, [0.0] * 8), (3002, [1.0, None] + [0.0] * 6), (3003, [float("nan")] * 8), (3004, [float("inf")] + [0.0] * 7), (3005, []), (None, rows[3][1]), (3006, [1.0, 2.0]), (3007, [2.0, 4.0]), (3008, [3e38] * 8), (3009, [1e-38] * 8)]
    df = spark.createDataFrame([(k, v, 1) for k, v in rows], "vec_id long, embedding array<float>, n int")
    got = sorted((tuple(r)[:3] for r in V.near_vectors(df).collect()), key=str)
    assert got == brute(rows)
    assert V.near_vectors(df.limit(0)).count() == 0


def test_tile_pairs_cover_everything_near(spark):
    r = random.Random(1)
    lo = np.array([[r.random() * 5, r.random() * 5] for _ in range(21)])
    lo = lo[np.lexsort(lo.T[::-1])]
    hi = lo + 0.3
    want = {(i, j) for i in range(21) for j in range(i, 21) if V._near(lo[i], hi[i], lo[j], hi[j], 0.5)}
    boxes = spark.createDataFrame([(i, lo[i].tolist(), hi[i].tolist()) for i in range(21)], "tile long, lo array<double>, hi array<double>")
    got = [(x["a"], x["b"]) for x in V.near_tiles(boxes, 21, 2, 0.5).collect()]
    assert set(got) == want and len(got) == len(want)
    assert [tuple(x) for x in V.near_tiles(boxes.limit(1), 1, 2, 0.5).collect()] == [(0, 0)]
