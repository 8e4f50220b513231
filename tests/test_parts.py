import numpy as np
import pytest
from pyspark.sql import functions as F

from foldstar import measures, planner, synth
from foldstar.functions import udfs
from foldstar.normalized import FactoredMatrix
from foldstar.operators import links
from foldstar.schema import FeatureSpec, binarize, packed
from foldstar.sources import tables

SF = "/root/testdata/sf0.001"


def test_sparse_equals_wide(spark):
    a = spark.createDataFrame([(1, "x", 2.0, "p q p"), (2, "y", 0.0, "q"), (3, "x", 5.0, ""), (4, None, 1.0, None)], "k long, c string, v double, t string")
    e = spark.createDataFrame([(i, i % 4 + 1, float(i)) for i in range(12)], "id long, k long, x double")
    spec = FeatureSpec(numeric={"v": F.col("v")}, onehot={"c": None}, key_onehot=True)
    coo = spec.coo(a, "k")
    t = FactoredMatrix.star(e, [(coo, "k", "k", [])], ["x"], ["id"])
    w = FactoredMatrix.star(e, [(coo.wide(), "k", "k", [])], ["x"], ["id"])
    T = w.materialize().collect()
    assert t.names == ["x", "v", "c_0", "c_1", "k#0", "k#1", "k#2", "k#3"]
    assert (t.gram() == T.T @ T).all() and (t.col_sums() == T.sum(axis=0)).all() and t.sum() == T.sum()
    x = np.arange(16.0).reshape(8, 2)
    a1 = sorted(map(tuple, (t @ x).frame.select("id", "_v0", "_v1").collect()))
    a2 = sorted(map(tuple, (w @ x).frame.select("id", "_v0", "_v1").collect()))
    assert a1 == a2 and ((t**2).col_sums() == (T**2).sum(axis=0)).all()
    with pytest.raises(ValueError):
        t + 1
    assert (t[["x", "c_1", "k=2"]].gram() == w[["x", "c_1", "k=2"]].gram()).all()
    hashed = FeatureSpec(hashed=["t"], bits=4).coo(a, "k")
    assert hashed.df.agg(F.sum("val")).first()[0] == 4


def test_packed_and_binarize(spark):
    e = spark.read.parquet(f"{SF}/embeddings.parquet")
    b = packed(e, "vec_id", "embedding", 8)
    assert len(b.names) == 8 and b.df.count() == e.count()
    r = spark.createDataFrame([(1.0,), (3.0,)], "x double").select(binarize(F.col("x"), 2), binarize(F.col("x"), 2, "01")).collect()
    assert [tuple(x) for x in r] == [(-1.0, 0.0), (1.0, 1.0)]


def test_plan_star_and_vstack(spark):
    t = synth.key_join(spark, 40, 2, [(4, 4), (30, 3)])
    p, verdicts = planner.plan_star(t)
    assert verdicts == [True, False] and len(p.links) == 1 and p.d == t.d
    order = [p.names.index(n) for n in t.names]
    assert (p.gram()[np.ix_(order, order)] == t.gram()).all()
    v = t.filter_rows("id < 10").vstack(t.filter_rows("id >= 10"))
    assert (v.gram() == t.gram()).all()
    assert measures.difference(t.gram(), t.materialize().gram()) == {"max_abs": 0.0, "max_rel": 0.0}
    assert t.stats()["links"][0]["tuple_ratio"] == 10


def test_links(spark):
    bands = spark.createDataFrame([(0, 0.0, 10.0), (1, 10.0, 35.0)], "band long, lo double, hi double")
    got = links.range_link(spark.createDataFrame([(9.9,), (10.0,), (34.9,), (35.0,)], "v double"), "v", bands, "lo", "hi", "band", 7.0)
    assert sorted(map(tuple, got.collect())) == [(9.9, 0), (10.0, 1), (34.9, 1)]
    ev = spark.createDataFrame([(1, 5), (1, 1), (2, 9)], "u long, t long")
    st = spark.createDataFrame([(1, 2, 100), (1, 5, 101), (1, 6, 102)], "u long, t long, s long")
    assert sorted(map(tuple, links.asof_link(ev, "u", "t", st, "u", "t", "s").collect()), key=str) == [(1, 1, None), (1, 5, 101), (2, 9, None)]


def test_sources(spark, tmp_path):
    df = spark.createDataFrame([(1, 2.5, "a"), (2, 3.5, "b")], "id long, v double, c string")
    for kind, read in (("csv", lambda p: tables.scan_csv(spark, p, "id long, v double, c string")), ("json", lambda p: tables.scan_json(spark, p, "id long, v double, c string")), ("orc", lambda p: tables.scan_orc(spark, p)), ("parquet", lambda p: spark.read.parquet(p))):
        p = str(tmp_path / kind)
        tables.write(df, p, kind)
        assert sorted(map(tuple, read(p).select("id", "v", "c").collect())) == [(1, 2.5, "a"), (2, 3.5, "b")]
    tables.write(df, "", "noop")
    x = np.array([[1.0, 2.0], [3.0, 4.0]])
    assert (tables.to_array(tables.from_array(spark, x), ["x0", "x1"], "id") == x).all()
    tables.save_model(str(tmp_path / "m.json"), ["a", "b"], w=x)
    assert (tables.load_model(str(tmp_path / "m.json"))["w"] == x).all()
    plan = tables.scan(spark, SF, "orders", ["o_orderkey"], F.col("o_custkey") < 5)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters" in plan and "LessThan(o_custkey,5)" in plan and "o_totalprice" not in plan.split("ReadSchema")[1]


def test_udfs(spark):
    df = spark.createDataFrame([(i, [float(i), 0.0, 2.0 * i]) for i in range(6)], "k long, v array<double>")
    x = np.array([[i, 0.0, 2.0 * i] for i in range(6)])
    assert np.allclose(np.array(df.agg(udfs.gram_of_packed("v")).first()[0]).reshape(3, 3), x.T @ x)
    flat = df.select("k", *[F.col("v")[j].alias(f"x{j}") for j in range(3)])
    got = {(r["r"], r["s"]): r["value"] for r in udfs.kernel_tiles(flat, "k", ["x0", "x1", "x2"], tile=2).collect()}
    assert got == {(i, j): float(x[i] @ x[j]) for i in range(6) for j in range(i, 6)}
    spark.udtf.register("coo_explode", udfs.CooExplode)
    df.createOrReplaceTempView("packed_rows")
    rows = spark.sql("SELECT k, col, val FROM packed_rows, LATERAL coo_explode(v)").collect()
    assert len(rows) == 10
    assert abs(df.select(udfs.sigmoid(F.lit(0.0))).first()[0] - 0.5) < 1e-12
