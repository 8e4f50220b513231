"""Products, row-side forms, integrity and wide sparse blocks, against numpy."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from foldstar.matrix import RowPseudoInverse
from foldstar.normalized import FactoredMatrix, Wide
from foldstar.schema import FeatureSpec, numbered
from tests.compare import assert_same


def small(spark, n=6, own=1, width=4, extra=0):
    rows = spark.createDataFrame([(i, i % 3, *[float((5 * i + k) % 7) for k in range(own)]) for i in range(n)], "_row long, j long" + "".join(f", u{k} double" for k in range(own)))
    block = spark.createDataFrame([(t, *[float((t * t + k + extra) % 5) for k in range(width)]) for t in range(3)], "id long" + "".join(f", x{k} double" for k in range(width)))
    return FactoredMatrix.star(rows, [(block, "j", "id", [f"x{k}" for k in range(width)])], [f"u{k}" for k in range(own)], ["_row"])


def dense(t):
    return t.materialize().frame.orderBy("_row").select(*t.names).toPandas().to_numpy(dtype=float)


def values(r):
    return r.frame.orderBy("_row").select(*r.cols).toPandas().to_numpy(dtype=float)


def test_products_with_arrays_on_the_left(spark):
    t = small(spark)
    x = np.arange(12.0).reshape(2, 6)
    assert np.allclose(x @ t, x @ dense(t))
    y = np.arange(10.0).reshape(2, 5)
    assert np.allclose(values((y @ t.T).T), dense(t) @ y.T)


def test_both_transposed(spark):
    a, b = small(spark, 5, 1, 5), small(spark, 6, 2, 3)  # a is 5 x 6, b is 6 x 5: a^T b^T is (b a)^T
    assert np.allclose(values((a.T @ b.T).T), dense(b) @ dense(a))


def test_rows_against_rows(spark):
    a, b = small(spark, 6, 1, 4), small(spark, 4, 3, 2)
    got = np.zeros((6, 4))
    for r in (a @ b.T).collect():
        got[r["r"], r["s"]] = r["value"]
    assert np.allclose(got, dense(a) @ dense(b).T)


def test_row_gram_keeps_ids(spark):
    t = small(spark)
    named = t.on(t.rows.withColumn("name", F.concat(F.lit("n"), (9 - F.col("_row")).cast("string"))))
    x = dense(t)
    got = {(r["r"], r["s"]): r["value"] for r in named.T.gram("name").collect()}
    assert got == {(f"n{9 - i}", f"n{9 - j}"): float(x[i] @ x[j]) for i in range(6) for j in range(6) if 9 - i <= 9 - j}
    with pytest.raises(ValueError):
        t.T.gram("j")


def test_pseudo_inverse_of_few_rows(spark):
    t = small(spark, 4, 1, 6)
    p = t.ginv()
    assert isinstance(p, RowPseudoInverse)
    x = dense(t)
    assert np.allclose(p.dense, np.linalg.pinv(x), atol=1e-8)
    b = t.row_matrix("_row")
    assert np.allclose(p @ b, np.linalg.pinv(x) @ np.arange(4.0).reshape(-1, 1), atol=1e-7)
    tall = small(spark, 40, 1, 2)
    q = tall.ginv()
    assert not isinstance(q, RowPseudoInverse)
    assert np.allclose(values(q.rows()).T, np.linalg.pinv(dense(tall)), atol=1e-8)


def test_repeated_target_keys_raise(spark):
    e = spark.createDataFrame([(1, 2.0)], "j long, u double")
    block = spark.createDataFrame([(1, 1.0), (1, 5.0)], "id long, x double")
    with pytest.raises(ValueError, match="repeat"):
        FactoredMatrix.star(e, [(block, "j", "id", ["x"])], ["u"])


def test_sum_of_matrices_with_the_same_links(spark):
    a, b = small(spark), small(spark, extra=2)
    assert np.allclose(dense(a + b), dense(a) + dense(b)) and np.allclose(dense(a - b), dense(a) - dense(b))
    with pytest.raises(ValueError):
        a.plus(small(spark, width=3))


def test_a_constant_shift_keeps_the_link_but_a_product_of_ones_does_not(spark):
    """Adding 1 to every cell is factored; adding a matrix that differs within a target's rows is not, and raises."""
    t = small(spark)
    assert np.allclose(dense(t + 1), dense(t) + 1)
    other = FactoredMatrix(t.rows.withColumnRenamed("j", "k"), t.own, [type(t.links[0])("k", t.links[0].block)])
    with pytest.raises(ValueError):
        t + other


def test_cartesian_by_one_join_value(spark):
    a = Wide(spark.createDataFrame([(1, 2.0), (2, 3.0)], "a long, x double"), "a", ["x"])
    b = Wide(spark.createDataFrame([(1, 5.0), (2, 7.0), (3, 1.0)], "b long, y double"), "b", ["y"])
    t = FactoredMatrix.mn(a, b)
    assert t.n_rows() == 6 and t.col_sums().tolist() == [15.0, 26.0]
    assert t.gram().tolist() == [[39.0, 65.0], [65.0, 150.0]]


def test_keys_are_numbered_without_the_driver(spark):
    df = spark.createDataFrame([(f"k{i % 40:02d}",) for i in range(200)] + [(None,)], "key string")
    got = sorted((r["key"], r["col"]) for r in numbered(df, "key", 5).collect())
    assert got == [(f"k{i:02d}", i + 5) for i in range(40)]
    attr = spark.createDataFrame([(i, f"c{i % 2}") for i in range(10)], "id long, kind string")
    coo = FeatureSpec(onehot={"kind": None}, key_onehot=True).coo(attr, "id")
    assert len(coo.names) == 12 and coo.names[2] == "id#0"
    t = FactoredMatrix.star(spark.range(30).select((F.col("id") % 10).alias("j")), [(coo, "j", "id", [])], [])
    x = dense(t.on(t.rows.withColumn("_row", F.monotonically_increasing_id())))
    want = {(i, j): v for (i, j), v in np.ndenumerate(x.T @ x) if i <= j and v}
    assert {(r["i"], r["j"]): r["value"] for r in t.gram_long().collect()} == want
    assert t.stats(cells=True)["nnz"] == 60


def test_statistics_of_the_gram(spark):
    t = small(spark, 30, 2, 3)
    x = dense(t)
    assert np.allclose(np.nan_to_num(t.corr()), np.nan_to_num(np.corrcoef(x.T)))
    w, v = t.pca(2)
    assert np.allclose(w, np.linalg.eigvalsh(np.cov(x.T))[::-1][:2])
    s, _ = t.svd_gram(2)
    assert np.allclose(s, np.linalg.svd(x)[1][:2])
    assert np.allclose(t.map("pow", 3).col_sums(), (x**3).sum(axis=0))


def test_invertibility_bound_reads_lineitem(spark):
    from foldstar.plans import queries as Q

    got = Q.QUERIES["invertibility_bound"](spark, "/root/testdata/sf0.001")
    lines = spark.read.parquet("/root/testdata/sf0.001/lineitem.parquet").select("l_linenumber").distinct().count()
    assert got.count() == 4 * lines and {r["possible"] for r in got.collect()} == {True, False}
    assert_same(got, Q.ORACLES["invertibility_bound"], "/root/testdata/sf0.001")
