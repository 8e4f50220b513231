import numpy as np
import pytest
from pyspark.sql import functions as F

from foldstar import algos, baselines, cost, dense, planner, synth
from foldstar.double import crossprod, outer, product
from foldstar.keyed import KeyedJoin
from foldstar.matrix import Transposed
from foldstar.normalized import FactoredMatrix, Wide


@pytest.fixture(scope="module")
def pair(spark):
    t = synth.key_join(spark, 60, 2, [(7, 3), (5, 2)])
    t.rows.persist()
    return t, t.materialize()


def frame(r):
    return np.array(sorted(map(tuple, r.frame.select("id", *r.cols).collect())))[:, 1:]


def test_elementwise_and_sums(pair):
    t, m = pair
    for f in (lambda x: x + 2, lambda x: 2 - x, lambda x: x * 3, lambda x: x / 4, lambda x: 5 / (x + 1), lambda x: x**2, lambda x: 2**x, lambda x: x.map("log") if False else (x + 1).map("log"), lambda x: x.exp(), lambda x: x.map("sin"), lambda x: x % 3, lambda x: x > 4, lambda x: x.clip(2, 5), lambda x: ((2 * x) + 1).exp()):
        a, b = f(t), f(m)
        assert isinstance(a, FactoredMatrix)
        np.testing.assert_allclose(a.col_sums(), b.col_sums(), rtol=1e-12)
        np.testing.assert_allclose(a.sum(), b.sum(), rtol=1e-12)
    assert (frame(t.row_sums()) == frame(m.row_sums())).all()
    assert (t.T.row_sums() == m.col_sums()).all() and t.T.T is t and isinstance(t.T + 1, Transposed)
    np.testing.assert_allclose(t.col_var(), m.collect().var(axis=0), rtol=1e-9)
    np.testing.assert_allclose(t.cov(), np.cov(m.collect().T), atol=1e-9)


def test_products(pair):
    t, m = pair
    g = np.random.default_rng(0)
    x = g.integers(-3, 4, size=(t.d, 3))
    assert (frame(t @ x) == frame(m @ x)).all()
    assert (frame(t.scored(x.astype(float), "lookup_first")) == frame(m @ x)).all()
    r, q = t @ x, m @ x
    assert (t.T @ r == m.T @ q).all() and ((r @ t if False else t.folded(r).T) == (m.T @ q).T).all()
    T = m.collect()
    for how in ({}, {"method": "naive"}, {"pairs": "cooc"}):
        assert (t.gram(**how) == T.T @ T).all()
    np.testing.assert_allclose(t.gram(weighting="sqrt"), T.T @ T, rtol=1e-12)
    assert (crossprod(t) == T.T @ T).all() and (crossprod(t, t) == T.T @ T).all() and (product(t.T, t) == T.T @ T).all()
    for lane in ("sql", "arrow"):
        assert (dense.products(m.frame, m.names, lane=lane) == T.T @ T).all()
    k = {(a["r"], a["s"]): a["value"] for a in t.T.gram("id").collect()}
    assert len(k) == 60 * 61 // 2 and abs(sum(v for (a, b), v in k.items() if a == b) - (T * T).sum()) < 1e-6
    b = t.cooc_bounds(0, 1)
    n = t.cooc(0, 1)
    assert b["low"] <= n.count() <= b["high"] and n.agg(F.sum("_c")).first()[0] == 60


def test_inverse(pair):
    t, m = pair
    T = m.collect()
    np.testing.assert_allclose(t.solve(t.row_matrix("y"))[:, 0], np.linalg.lstsq(T, np.array(m.frame.select("y").toPandas())[:, 0], rcond=None)[0], atol=1e-8)
    p = t.ginv()
    np.testing.assert_allclose(p @ t.row_matrix("y"), np.linalg.pinv(T) @ np.array(m.frame.select("y").toPandas()), atol=1e-8)
    P = np.linalg.pinv(T).T
    got = p.rows().frame.select("id", *p.rows().cols).orderBy("id").toPandas().to_numpy()[:, 1:]
    order = np.argsort(np.array(m.frame.select("id").toPandas())[:, 0])
    np.testing.assert_allclose(got, P[order], atol=1e-8)


def test_algorithms(pair):
    t, m = pair
    T = m.collect()
    y = np.array(m.frame.select("y").toPandas())[:, 0]
    for fn in (lambda a: algos.logistic_gd(a, "y", alpha=1e-4, iters=3), lambda a: algos.linreg_normal(a, "y"), lambda a: algos.linreg_gd(a, "y", alpha=1e-5, iters=3), lambda a: algos.linreg_cofactor(a, "y", alpha=1e-5, iters=3), lambda a: algos.linreg_cofactor(a, "y", alpha=0.1, iters=3, step="adagrad")):
        np.testing.assert_allclose(fn(t), fn(m), rtol=1e-9)
    w = np.zeros(t.d)
    for _ in range(3):
        w = w + 1e-4 * T.T @ (y / (1 + np.exp(y * (T @ w))))
    np.testing.assert_allclose(algos.logistic_gd(t, "y", alpha=1e-4, iters=3), w, rtol=1e-9)
    np.testing.assert_allclose(algos.linreg_gd(t, "y", alpha=1e-5, iters=3), algos.linreg_cofactor(t, "y", alpha=1e-5, iters=3), rtol=1e-9)
    c0 = T[:3].T.copy()
    c1, a1 = algos.kmeans(t, c0, 3)
    c2, a2 = algos.kmeans(m, c0, 3)
    np.testing.assert_allclose(c1, c2)
    c = c0
    for _ in range(3):
        lab = ((T[:, :, None] - c[None]) ** 2).sum(axis=1).argmin(axis=1)
        c = np.stack([T[lab == j].mean(axis=0) for j in range(3)], axis=1)
    np.testing.assert_allclose(c1, c)
    w0 = [((F.col("id") * (7 + j)) % 10 + 1) / 10.0 for j in range(2)]
    h0 = np.arange(1, 2 * t.d + 1).reshape(t.d, 2) / 10
    (wa, ha), (wb, hb) = algos.gnmf(t, w0, h0, 2), algos.gnmf(m, w0, h0, 2)
    np.testing.assert_allclose(ha, hb)
    np.testing.assert_allclose(frame(wa), frame(wb))
    ids = np.array(m.frame.select("id").toPandas())[:, 0]
    W, H = np.stack([((ids * (7 + j)) % 10 + 1) / 10.0 for j in range(2)], axis=1), h0
    for _ in range(2):
        H = H * (T.T @ W) / (H @ (W.T @ W))
        W = W * (T @ H) / (W @ (H.T @ H))
    np.testing.assert_allclose(ha, H)
    for kind, arg in (("sse", w), ("log", w)):
        np.testing.assert_allclose(algos.loss(t, arg, "y", kind), algos.loss(m, arg, "y", kind))
    np.testing.assert_allclose(algos.loss(t, c, kind="inertia"), ((T[:, :, None] - c[None]) ** 2).sum(axis=1).min(axis=1).sum())
    e = synth.key_join(t.rows.sparkSession, 60, 2, [(7, 3)])
    got = baselines.hash_glm(e.rows, e.own, "k0", e.links[0].block.df, "id", e.links[0].block.names, "y", 1e-4, 3)
    np.testing.assert_allclose(got, algos.logistic_gd(e, "y", alpha=1e-4, iters=3), rtol=1e-9)


def test_ties_and_empty(spark):
    t = FactoredMatrix(spark.createDataFrame([(0, 0.0), (1, 2.0), (2, 1.0)], "id long, x double"), ["x"], [])
    c, a = algos.kmeans(t, np.array([[0.0, 2.0, 99.0]]), 1, ties="all")
    assert a.col_sums().tolist() == [2, 2, 0] and c.tolist() == [[0.5, 1.5, 99.0]]
    c, a = algos.kmeans(t, np.array([[0.0, 2.0, 99.0]]), 1, empty="nan")
    assert a.col_sums().tolist() == [2, 1, 0] and np.isnan(c[0, 2])


def test_many_to_many(spark):
    a, b = synth.many_to_many(spark, 30, 2, 4)
    t = FactoredMatrix.mn(synth.wide(a, "a", 2), synth.wide(b, "b", 2), a.select("id", "j"), b.select("id", "j"))
    T = t.materialize().collect()
    k = KeyedJoin([(a, ["a0", "a1"]), (b, ["b0", "b1"])], [("j", "j")])
    assert k.n_rows() == len(T) and (k.gram() == T.T @ T).all() and (t.gram() == T.T @ T).all() and (k.col_sums() == T.sum(axis=0)).all() and (t.gram(method="naive") == T.T @ T).all()
    c, _ = synth.many_to_many(spark, 12, 2, 3, seed=9)
    c = c.select("id", F.col("a0").alias("c0"), (F.col("id") % 5).alias("v"))
    b2 = b.withColumn("u", F.col("id") % 5)
    chain = FactoredMatrix.chain([synth.wide(a, "a", 2), synth.wide(b, "b", 2), Wide(c, "id", ["c0"])], [a, b2, c], [("j", "j"), ("u", "v")])
    T = chain.materialize().collect()
    k = KeyedJoin([(a, ["a0", "a1"]), (b2, ["b0", "b1"]), (c, ["c0"])], [("j", "j"), ("u", "v")])
    assert k.n_rows() == len(T) and (k.gram() == T.T @ T).all() and (chain.gram() == T.T @ T).all()
    k = KeyedJoin([(a, ["a0"]), (c, ["c0"])], None)
    assert k.n_rows() == 360


def test_double(spark):
    a = synth.key_join(spark, 20, 2, [(5, 3)])
    b = synth.key_join(spark, 5, 3, [(2, 2)], seed=5)
    b.rows = b.rows.withColumn("_row", F.col("id"))
    A, B = a.materialize(), b.materialize()
    x = A.frame.orderBy("id").select(*a.names).toPandas().to_numpy()
    y = B.frame.orderBy("id").select(*b.names).toPandas().to_numpy()
    assert (frame(a @ b) == x @ y).all()
    a.rows = a.rows.withColumn("_row", F.col("id"))
    got = outer(b, a)
    z = np.zeros((5, 20))
    for r in got.collect():
        z[r["r"], r["s"]] = r["value"]
    assert (z == y @ x.T).all()


def test_dangling_and_edges(spark):
    e = spark.createDataFrame([(1, 1, 2.0), (2, None, 3.0), (3, 9, 4.0), (4, 1, 5.0)], "id long, k long, x double")
    a = spark.createDataFrame([(1, 7.0), (5, 8.0)], "k long, z double")
    t = FactoredMatrix.star(e, [(a, "k", "k", ["z"])], ["x"], ["id"])
    assert t.n_rows() == 2 and t.col_sums().tolist() == [7.0, 14.0] and t.gram().tolist() == [[29.0, 49.0], [49.0, 98.0]]
    assert t.trimmed().links[0].block.df.count() == 1
    none = FactoredMatrix.star(e.limit(0), [(a, "k", "k", ["z"])], [])
    assert none.gram().tolist() == [[0.0]] and none.sum() == 0.0
    assert FactoredMatrix.star(e, [(a, "k", "k", ["z"])], ["x"], total=True).validate() == {"k": {"repeated": 0, "dangling": 2}}


def test_cost_and_rule():
    d = cost.Dims(10**9, 20, ((10**3, 40),))
    for op in ("scalar", "lmm", "gram"):
        assert cost.speedup(op, d) == pytest.approx(cost.limit(op, d.tuple_ratio, d.feature_ratio, "TR"), rel=1e-3)
    wide = cost.Dims(10**4, 1, ((10**3, 10**8),))
    for op in ("scalar", "lmm", "gram"):
        assert cost.speedup(op, wide) == pytest.approx(cost.limit(op, 10, 0, "FR"), rel=1e-2)
    assert planner.should_factor(5, 1) and not planner.should_factor(4.9, 9) and not planner.should_factor(50, 0.9)
    runs = [planner.Run(2, 1, 1, 2), planner.Run(6, 0.5, 1, 1.5), planner.Run(10, 2, 4, 1), planner.Run(20, 4, 9, 1)]
    tau, rho = planner.tune_rule(runs)
    assert planner.judge_rule(runs, tau, rho)["go_wrong"] == 0 and planner.judge_rule(runs)["go_right"] == 2
    assert not cost.invertible_possible(3, 1) and cost.invertible_possible(2, 1)
