"""kernel_extremes joins each part's class and the two free columns, never the joined features."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from foldstar import extremes
from foldstar.normalized import FactoredMatrix
from foldstar.workloads import FIXTURES

SF = "/root/testdata/sf0.001"


def brute(t, on="o_orderkey"):
    x = np.array([[float(r[c]) for c in [on, *t.names]] for r in t.materialize().frame.collect()]).reshape(-1, t.d + 1)
    g = x[:, 1:] @ x[:, 1:].T
    return {int(k): (len(x), a, b) for k, a, b in zip(x[:, 0], g.min(axis=1), g.max(axis=1))} if len(x) else {}


def read(df, on="o_orderkey"):
    return {r[on]: (r["n"], r["smallest"], r["largest"]) for r in df.collect()}


@pytest.mark.parametrize("chunk", [1, 7, 1 << 18])
def test_no_row_of_features_is_made(spark, monkeypatch, chunk):
    t = FIXTURES["oc"].build(spark, SF)
    want = brute(t)
    monkeypatch.setattr(extremes, "CHUNK", chunk, raising=False)
    monkeypatch.setattr(extremes, "FEW", 2)
    monkeypatch.setattr(FactoredMatrix, "materialize", lambda *a: pytest.fail("the joined table was made"))
    assert read(t.kernel_extremes("o_orderkey", ("o_total", "c_bal"))) == want


def made(spark, own, block):
    rows = spark.createDataFrame([(i, i % len(block), *map(float, r)) for i, r in enumerate(own)], "o_orderkey long, fk long, a double, u double")
    targets = spark.createDataFrame([(i, *map(float, r)) for i, r in enumerate(block)], "k long, b double, c double, v double")
    return FactoredMatrix.star(rows, [(targets, "fk", "k", ["b", "c", "v"])], ["a", "u"], ["o_orderkey"])


def test_many_rows_of_a_class(spark):
    r = np.random.default_rng(4)
    t = made(spark, np.stack([r.integers(0, 3, 900), r.integers(-50, 50, 900)], axis=1), np.stack([r.integers(-1, 2, 40), r.integers(0, 2, 40), r.integers(-60, 60, 40)], axis=1))
    assert read(t.kernel_extremes("o_orderkey", ("u", "v"))) == read(t.kernel_extremes("o_orderkey", ("v", "u"))) == brute(t)
    # both free columns in one part, and none of a class
    assert read(t.kernel_extremes("o_orderkey", ("b", "v"))) == read(t.kernel_extremes("o_orderkey", ("a", "u"))) == brute(t)


def test_odd_values_and_no_rows(spark):
    own = np.array([[0.0, 1.0], [-0.0, 2.0], [1.0, -3.0]])
    t = made(spark, own, [[0.0, -0.0, 5.0], [-0.0, 0.0, -7.0]])
    assert read(t.kernel_extremes("o_orderkey", ("u", "v"))) == brute(t)
    assert read(t.on(t.rows.where("o_orderkey < 0")).kernel_extremes("o_orderkey", ("u", "v"))) == {}
    met = []
    odd = t.on(t.rows.withColumn("u", F.when(F.col("o_orderkey") == 1, F.lit(float("nan"))).otherwise(F.col("u"))))
    odd.kernel_blocks = lambda *a, **k: met.append(1)
    odd.kernel_extremes("o_orderkey", ("u", "v"))
    assert met
