import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from foldstar import extremes
from foldstar.normalized import FactoredMatrix
from foldstar.plans import queries as Q
from foldstar.workloads import FIXTURES

SF = "/root/testdata/sf0.001"


def test_all_blocks_against_brute_force(spark):
    t = FIXTURES["oc"].build(spark, SF)
    rows = {r["o_orderkey"]: np.array([float(r[c]) for c in t.names]) for r in t.materialize().frame.collect()}
    ids = sorted(rows)
    x = np.stack([rows[i] for i in ids])
    g = x @ x.T
    flat = lambda a, b, v: pd.DataFrame({"r": np.repeat(a, len(b)), "s": np.tile(b, len(a)), "v": v.ravel()})
    got = t.kernel_blocks("o_orderkey", flat, "r long, s long, v double", block=200).toPandas().sort_values(["r", "s"])
    assert len(got) == len(ids) ** 2 and (got["v"].to_numpy().reshape(g.shape) == g).all()


def test_every_order_is_there(spark):
    n = spark.read.parquet(f"{SF}/orders.parquet").count()
    got = Q.QUERIES["kernel_all_rows_oc"](spark, SF).collect()
    assert len(got) == n > 60 and {r["n"] for r in got} == {n}


def test_kernel_beyond_the_short_form(spark):
    t = FIXTURES["sn"].build(spark, SF)
    rows = lambda m: sorted(tuple(r) for r in t.T.gram("s_suppkey", max_rows=m).collect())
    assert rows(1) == rows(5000) and len(rows(1)) == t.n_rows() * (t.n_rows() + 1) // 2


def test_kernel_beyond_the_short_form_refuses_repeated_ids(spark):
    t = FIXTURES["sn"].build(spark, SF)
    with pytest.raises(ValueError):
        t.on(t.rows.withColumn("s_suppkey", F.lit(1))).kernel("s_suppkey", max_rows=1)


def test_extremes_meet_corners_only(spark, monkeypatch):
    t = FIXTURES["oc"].build(spark, SF)
    x = np.array([[float(r[c]) for c in ["o_orderkey", *t.names]] for r in t.materialize().frame.collect()])
    g = x[:, 1:] @ x[:, 1:].T
    want = {int(k): (len(x), a, b) for k, a, b in zip(x[:, 0], g.min(axis=1), g.max(axis=1))}
    read = lambda df: {r["o_orderkey"]: (r["n"], r["smallest"], r["largest"]) for r in df.groupBy("o_orderkey").agg(F.sum("n").alias("n"), F.min("smallest").alias("smallest"), F.max("largest").alias("largest")).collect()}
    assert read(t.kernel_extremes("o_orderkey", ("o_total", "c_bal"), most=0)) == want
    monkeypatch.setattr(FactoredMatrix, "kernel_blocks", lambda *a, **k: pytest.fail("all blocks were met"))
    assert read(t.kernel_extremes("o_orderkey", ("o_total", "c_bal"))) == want
    for few, levels in ((1, 64), (10**9, 64)):
        monkeypatch.setattr(extremes, "FEW", few)
        assert read(t.kernel_extremes("o_orderkey", ("o_total", "c_bal"))) == want


def test_hull_keeps_every_extreme():
    hull, by_class = extremes._tools()
    rng = np.random.default_rng(1)
    for n, size in ((1, 5), (5, 3), (70, 3), (300, 4), (500, 1000), (400, 1)):
        p = rng.integers(0, size, (n, 2)).astype(float)
        w = rng.normal(size=(2, 200))
        kept = p[hull(p[:, 0], p[:, 1])]
        assert ((p @ w).max(axis=0) <= (kept @ w).max(axis=0) + 1e-9).all() and ((p @ w).min(axis=0) >= (kept @ w).min(axis=0) - 1e-9).all()
    line = np.stack([np.arange(200.0), 2 * np.arange(200.0)], axis=1)
    kept = line[hull(line[:, 0], line[:, 1])]
    assert [0.0, 0.0] in kept.tolist() and [199.0, 398.0] in kept.tolist()
