"""Registered queries of the linear-algebra engine, each with SQL that joins first."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from foldstar import algos, cost, planner
from foldstar.double import cross
from foldstar.matrix import RowMatrix
from foldstar.workloads import FIXTURES, PART33, SUPP31, TARGETS, Fixture, emb, keyed, self_join, thinned, with_keys

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query: Callable, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLES[name] = sql


def vector(spark, names, values, digits: int | None = None) -> DataFrame:
    fix = (lambda v: round(float(v), digits) + 0.0) if digits is not None else (lambda v: float(v) + 0.0)
    return spark.createDataFrame([(n, fix(v)) for n, v in zip(names, values)], "feature string, value double")


def upper(spark, names, g, digits: int | None = None) -> DataFrame:
    fix = (lambda v: round(float(v), digits) + 0.0) if digits is not None else (lambda v: float(v) + 0.0)
    rows = [(a, names[j], fix(g[i, j])) for i, a in enumerate(names) for j in range(i, len(names))]
    return spark.createDataFrame(rows, "i string, j string, value double")


def block_rows(spark, left, right, g) -> DataFrame:
    return spark.createDataFrame([(a, b, float(g[i, j]) + 0.0) for i, a in enumerate(left) for j, b in enumerate(right)], "i string, j string, value double")


def keyed_rows(fx: Fixture, r: RowMatrix, names: list[str] | None = None) -> DataFrame:
    names = names or ["value"]
    return r.frame.select(*[F.col(c).cast("long").alias(i) for i, c in fx.ids.items()], *[(F.col(c) + 0.0).alias(n) for c, n in zip(r.cols, names)])


def _list(items) -> str:
    return "[" + ", ".join(items) + "]"


def sql_vector(fx: Fixture, cell: Callable[[str], str], cte: str = "") -> str:
    names = list(fx.features)
    return f"WITH t AS ({fx.sql(cte)}) SELECT unnest({_list(repr(n) for n in names)}) AS feature, unnest({_list(cell(n) for n in names)}) AS value FROM t"


def sql_pairs(fx: Fixture, cells: list[tuple[str, str]], value: Callable[[str, str], str]) -> str:
    return f"WITH t AS ({fx.sql()}) SELECT unnest({_list(repr(a) for a, _ in cells)}) AS i, unnest({_list(repr(b) for _, b in cells)}) AS j, unnest({_list(value(a, b) for a, b in cells)}) AS value FROM t"


def sql_ids(fx: Fixture) -> str:
    return ", ".join(f"{i}::BIGINT AS {i}" for i in fx.ids)


def weights(n: int, shift: int = 0) -> np.ndarray:
    """Small whole weights: the i-th is (i + shift) mod 5 less 2."""
    return np.array([(i + shift) % 5 - 2 for i in range(n)], dtype=float)


def sql_score(fx: Fixture, shift: int = 0) -> str:
    return " + ".join(f"({int(w)}) * {n}" for n, w in zip(fx.features, weights(len(fx.features), shift)))


def fixture(name):
    fx = FIXTURES[name]
    return fx, fx.build


def _first_id(fx: Fixture) -> tuple[str, str]:
    return next(iter(fx.ids.items()))


def _linear_algebra() -> None:
    for name in ("k1", "k2", "k2z", "k3", "d1", "oc", "mn", "eo", "ch"):
        fx, build = fixture(name)
        names = list(fx.features)
        cells = [(a, b) for i, a in enumerate(names) for b in names[i:]]
        rid, rcol = _first_id(fx)
        add(f"row_sums_{name}", lambda s, d, fx=fx: keyed_rows(fx, fx.build(s, d).row_sums()), f"WITH t AS ({fx.sql()}) SELECT {sql_ids(fx)}, {' + '.join(names)} AS value FROM t")
        add(f"col_sums_{name}", lambda s, d, fx=fx: vector(s, fx.features, fx.build(s, d).col_sums()), sql_vector(fx, lambda n: f"sum({n})"))
        add(f"total_sum_{name}", lambda s, d, fx=fx: s.createDataFrame([(fx.build(s, d).sum(),)], "value double"), f"WITH t AS ({fx.sql()}) SELECT sum({' + '.join(names)}) AS value FROM t")
        add(f"lmm_{name}", lambda s, d, fx=fx: keyed_rows(fx, fx.build(s, d) @ weights(len(fx.features))), f"WITH t AS ({fx.sql()}) SELECT {sql_ids(fx)}, {sql_score(fx)} AS value FROM t")

        def tlmm(s, d, fx=fx, rcol=rcol):
            t = fx.build(s, d)
            r = t.row_matrix(rcol).apply(lambda v: [v[0] % 7 - 3])
            return vector(s, fx.features, (t.T @ r)[:, 0])

        add(f"tlmm_{name}", tlmm, sql_vector(fx, lambda n, rid=rid: f"sum({n} * ({rid} % 7 - 3))"))

        def rmm(s, d, fx=fx, rcol=rcol):
            t = fx.build(s, d)
            r = t.row_matrix(rcol).apply(lambda v: [v[0] * 0 + 1, v[0] % 3])
            x = r @ t
            return s.createDataFrame([(i, n, float(x[i, j])) for i in range(2) for j, n in enumerate(fx.features)], "i int, feature string, value double")

        add(f"rmm_{name}", rmm, f"WITH t AS ({fx.sql()}) SELECT unnest({_list(['0'] * len(names) + ['1'] * len(names))})::INT AS i, unnest({_list(repr(n) for n in names * 2)}) AS feature, unnest({_list([f'sum({n})' for n in names] + [f'sum({n} * ({rid} % 3))' for n in names])}) AS value FROM t")
        add(f"gram_{name}", lambda s, d, fx=fx: upper(s, list(fx.features), fx.build(s, d).gram()), sql_pairs(fx, cells, lambda a, b: f"sum({a} * {b})"))
    for name in ("mn", "eo", "ch"):
        fx, _ = fixture(name)
        add(f"gram_keyed_{name}", lambda s, d, n=name, fx=fx: upper(s, list(fx.features), keyed(s, d, n).gram()), ORACLES[f"gram_{name}"])
        add(f"col_sums_keyed_{name}", lambda s, d, n=name, fx=fx: vector(s, fx.features, keyed(s, d, n).col_sums()), ORACLES[f"col_sums_{name}"])
        add(f"rows_keyed_{name}", lambda s, d, n=name: s.createDataFrame([(keyed(s, d, n).n_rows(),)], "n long"), f"SELECT count(*) AS n FROM {fx.tables}")
    for label, fn in (("naive_k1", lambda t: t.gram(method="naive")), ("sql_view_k1min", lambda t: t.gram())):
        fx, _ = fixture("k1" if "min" not in label else "k1min")
        names = list(fx.features)
        cells = [(a, b) for i, a in enumerate(names) for b in names[i:]]
        add(f"gram_{label}", lambda s, d, fx=fx, fn=fn: upper(s, list(fx.features), fn(fx.build(s, d))), sql_pairs(fx, cells, lambda a, b: f"sum({a} * {b})"))
    k2 = FIXTURES["k2"]
    add("gram_cooc_k2", lambda s, d: upper(s, list(k2.features), k2.build(s, d).gram(pairs="cooc")), ORACLES["gram_k2"])
    for name in ("k1", "k2", "k3"):
        add(f"m_gram_{name}", lambda s, d, fx=FIXTURES[name]: upper(s, list(fx.features), fx.build(s, d).materialize().gram()), ORACLES[f"gram_{name}"])
    fx1 = FIXTURES["k1min"]
    n1 = list(fx1.features)
    c1 = [(a, b) for i, a in enumerate(n1) for b in n1[i:]]
    add("gram_sqrt_k1min", lambda s, d: upper(s, n1, fx1.build(s, d).gram(weighting="sqrt"), 0), sql_pairs(fx1, c1, lambda a, b: f"round(sum({a} * {b}), 0)"))
    add("cov_k1min", lambda s, d: upper(s, n1, fx1.build(s, d).cov(), 2), sql_pairs(fx1, c1, lambda a, b: f"round((sum({a} * {b}) - sum({a}) * sum({b}) / count(*)) / (count(*) - 1), 2) + 0.0"))
    add("col_var_k1min", lambda s, d: vector(s, n1, fx1.build(s, d).col_var(), 2), sql_vector(fx1, lambda n: f"round(sum({n} * {n}) / count(*) - (sum({n}) / count(*)) * (sum({n}) / count(*)), 2)"))
    add("lmm_multi_k2", lambda s, d: keyed_rows(k2, k2.build(s, d) @ np.stack([weights(73, i) for i in range(3)], axis=1), ["v0", "v1", "v2"]), f"WITH t AS ({k2.sql()}) SELECT {sql_ids(k2)}, {', '.join(f'{sql_score(k2, i)} AS v{i}' for i in range(3))} FROM t")
    k1 = FIXTURES["k1"]
    add("lmm_lookup_first_k1", lambda s, d: keyed_rows(k1, k1.build(s, d).scored(weights(37).reshape(-1, 1), "lookup_first")), ORACLES["lmm_k1"])

    def dmm(method):
        def q(s, d):
            t = k2.build(s, d)
            a, b = t[[*k2.features][:9] + [n for n in k2.features if n.startswith("p_")]], t[[n for n in k2.features if n.startswith("s_")]]
            return block_rows(s, a.names, b.names, cross(a, b, method))
        return q

    left = [n for n in k2.features if not n.startswith("s_")]
    right = [n for n in k2.features if n.startswith("s_")]
    for method in ("hybrid", "cooc"):
        add(f"dmm_same_rows_{method}", dmm(method), sql_pairs(k2, [(a, b) for a in left for b in right], lambda a, b: f"sum({a} * {b})"))

    _double_products()
    oc, sn = FIXTURES["oc"], FIXTURES["sn"]
    dots = " + ".join(f"a.{n} * b.{n}" for n in oc.features)
    add("kernel_rows_sn", lambda s, d: sn.build(s, d).T.gram("s_suppkey"), f"WITH t AS ({sn.sql()}) SELECT a.s_suppkey::BIGINT AS r, b.s_suppkey::BIGINT AS s, {' + '.join(f'a.{n} * b.{n}' for n in sn.features)} AS value FROM t a JOIN t b ON a.s_suppkey <= b.s_suppkey")

    def kernel_all(s, d):
        parts = oc.build(s, d).kernel_extremes("o_orderkey", ("o_total", "c_bal"))
        return parts.groupBy("o_orderkey").agg(F.sum("n").alias("n"), (F.min("smallest") + 0.0).alias("smallest"), (F.max("largest") + 0.0).alias("largest"))

    add("kernel_all_rows_oc", kernel_all, f"WITH t AS ({oc.sql()}) SELECT a.o_orderkey::BIGINT AS o_orderkey, count(*) AS n, min({dots})::DOUBLE AS smallest, max({dots})::DOUBLE AS largest FROM t a, t b GROUP BY 1")

    # element-wise operators, reduced by column sums
    E = {
        "scalar_add": (lambda t: t + 2, "{0} + 2"), "scalar_rsub": (lambda t: 2 - t, "2 - {0}"), "scalar_sub": (lambda t: t - 3, "{0} - 3"), "scalar_mul": (lambda t: 3 * t, "3 * {0}"),
        "scalar_div": (lambda t: t / 4, "{0} / 4"), "scalar_rdiv": (lambda t: 5 / (t + 1), "5 / ({0} + 1)"), "scalar_pow": (lambda t: t**2, "{0} * {0}"), "scalar_mod": (lambda t: t % 7, "((({0} % 7) + 7) % 7)"),
        "scalar_gt": (lambda t: t > 4, "CAST({0} > 4 AS INT)"), "scalar_clip": (lambda t: t.clip(1, 9), "least(greatest({0}, 1), 9)"), "fn_log": (lambda t: (t + 1).map("log"), "ln({0} + 1)"),
        "fn_exp": (lambda t: (t / 100000).exp(), "exp({0} / 100000)"), "fn_sin": (lambda t: t.map("sin"), "sin({0})"), "fn_sqrt": (lambda t: t.map("sqrt"), "sqrt({0})"), "fn_tanh": (lambda t: (t / 1000).map("tanh"), "tanh({0} / 1000)"),
        "fn_sigmoid": (lambda t: (t / 100000).map("sigmoid"), "1 / (1 + exp(-({0} / 100000)))"), "scalar_chain": (lambda t: ((2 * t) + 1).map("sqrt"), "sqrt(2 * {0} + 1)"), "scalar_rpow": (lambda t: 2 ** (t / 100000), "pow(2, {0} / 100000)"),
    }
    for op, (fn, sql) in E.items():
        for name in ("k1", "k2"):
            fx, _ = fixture(name)
            if op in ("fn_log", "fn_sqrt", "scalar_chain", "scalar_rdiv") and name == "k2":
                continue  # account balances may be negative
            add(f"{op}_{name}", lambda s, d, fx=fx, fn=fn: vector(s, fx.features, fn(fx.build(s, d)).col_sums(), 3), sql_vector(fx, lambda n, sql=sql: f"round(sum(CAST({sql.format(n)} AS DOUBLE)), 3) + 0.0"))
    for name in ("mn", "ch", "d1"):
        fx, _ = fixture(name)
        for op in ("scalar_mul", "scalar_pow", "scalar_add"):
            fn, sql = E[op]
            add(f"{op}_{name}", lambda s, d, fx=fx, fn=fn: vector(s, fx.features, fn(fx.build(s, d)).col_sums()), sql_vector(fx, lambda n, sql=sql: f"sum(CAST({sql.format(n)} AS DOUBLE))"))
    d1 = FIXTURES["d1"]
    add("scalar_mul_rows_d1", lambda s, d: keyed_rows(d1, (3 * d1.build(s, d)).row_sums()), f"WITH t AS ({d1.sql()}) SELECT {sql_ids(d1)}, 3 * ({' + '.join(d1.features)}) AS value FROM t")

    def elementwise_all(s, d):
        t = fx1.build(s, d)
        x = t.rows.select("l_orderkey").distinct().select("l_orderkey", *[(F.col("l_orderkey") % 5 + 1.0).alias(n) for n in n1])
        return t.elementwise(x, "l_orderkey", lambda a, b: a * b).agg(*[F.sum(n).alias(n) for n in n1])

    add("elementwise_matrix_all_k1min", elementwise_all, f"WITH t AS ({fx1.sql()}) SELECT {', '.join(f'sum({n} * (l_orderkey % 5 + 1)) AS {n}' for n in n1)} FROM t")

    def penrose(s, d):
        t = fx1.build(s, d)
        g = t.gram()
        p = t.ginv()
        a = p.p @ g  # pinv(T) T
        scale = np.abs(g).max()
        return s.createDataFrame([("t p t", round(float(np.abs(g @ a - g).max() / scale), 6) + 0.0), ("p t p", round(float(np.abs(a @ p.p - p.p).max() / np.abs(p.p).max()), 6) + 0.0), ("symmetric", round(float(np.abs(a - a.T).max()), 3) + 0.0)], "condition string, residual double")

    add("ginv_penrose_k1min", penrose, "SELECT unnest(['t p t', 'p t p', 'symmetric']) AS condition, unnest([0.0, 0.0, 0.0])::DOUBLE AS residual")


def _double_products() -> None:
    """Products with a second factored matrix that is short: 31 rows to the right of T, or rows against T's rows."""
    sn = FIXTURES["sn"]
    names = list(sn.features)
    d = len(names)

    def right(s, rows: int, own: int, width: int):
        """`rows` numbered rows, `own` features of their own, the others from a block of three targets."""
        from foldstar.normalized import FactoredMatrix, Wide

        e = s.range(rows).select(F.col("id").alias("_row"), (F.col("id") % 3).alias("j"), *[((7 * F.col("id") + k) % 5).cast("double").alias(f"u{k}") for k in range(own)])
        block = Wide(s.range(3).select("id", *[((F.col("id") + k) % 4).cast("double").alias(f"x{k}") for k in range(own, width)]), "id", [f"x{k}" for k in range(own, width)])
        return FactoredMatrix.star(e, [(block, "j", "id", [])], [f"u{k}" for k in range(own)], ["_row"], total=True)

    cell = lambda r, k, own: (7 * r + k) % 5 if k < own else (r % 3 + k) % 4
    dots = [" + ".join(f"{cell(i, j, 2)} * {n}" for i, n in enumerate(names)) for j in range(4)]
    sql = f"WITH t AS ({sn.sql()}) SELECT {sql_ids(sn)}, {', '.join(f'{x} AS v{j}' for j, x in enumerate(dots))} FROM t"
    add("dmm_ab", lambda s, d_: keyed_rows(sn, sn.build(s, d_) @ right(s, d, 2, 4), [f"v{j}" for j in range(4)]), sql)
    add("dmm_atbt", lambda s, d_: keyed_rows(sn, (right(s, d, 2, 4).T @ sn.build(s, d_).T).T, [f"v{j}" for j in range(4)]), sql)
    # own widths: equal, T's narrower, T's wider than the right factor's
    for label, own in (("", 1), ("_narrow", 3), ("_wide", 0)):
        def abt(s, d_, own=own):
            t = sn.build(s, d_)
            t = t.on(t.rows.withColumn("_row", F.col("s_suppkey")))
            return (t @ right(s, 7, own, d).T).select("r", F.col("s").cast("int").alias("s"), "value")

        by = [" + ".join(f"{cell(r, k, own)} * {n}" for k, n in enumerate(names)) for r in range(7)]
        add(f"dmm_abt{label}", abt, f"WITH t AS ({sn.sql()}) SELECT s_suppkey::BIGINT AS r, unnest(range(7))::INT AS s, unnest({_list(by)}) AS value FROM t")
    for name in ("k1", "mn"):
        fx = FIXTURES[name]
        x = np.stack([weights(len(fx.features)), weights(len(fx.features), 1)])
        add(f"trmm_{name}", lambda s, d_, fx=fx, x=x: keyed_rows(fx, (x @ fx.build(s, d_).T).T, ["v0", "v1"]), f"WITH t AS ({fx.sql()}) SELECT {sql_ids(fx)}, {', '.join(f'{sql_score(fx, i)} AS v{i}' for i in range(2))} FROM t")
    mn, xx, k1 = FIXTURES["mn"], FIXTURES["xx"], FIXTURES["k1"]
    add("gram_mn_naive", lambda s, d_: upper(s, list(mn.features), mn.build(s, d_).gram(method="naive")), ORACLES["gram_mn"])
    pairs = [(a, b) for i, a in enumerate(xx.features) for b in list(xx.features)[i:]]
    add("gram_xx", lambda s, d_: upper(s, list(xx.features), xx.build(s, d_).gram()), sql_pairs(xx, pairs, lambda a, b: f"sum({a} * {b})"))
    oc = FIXTURES["oc"]
    add("plus_same_links_oc", lambda s, d_: vector(s, oc.features, (oc.build(s, d_) + 2 * oc.build(s, d_)).col_sums()), sql_vector(oc, lambda n: f"sum({n} + 2 * {n})"))


def _wide_sparse() -> None:
    """Keys as features: T is wider than a driver holds, so its Gram stays a table."""
    blocks = [("part", "p_partkey", "l_partkey", PART33, "part"), ("supp", "s_suppkey", "l_suppkey", SUPP31, "(SELECT s.*, n_regionkey FROM supplier s JOIN nation ON s_nationkey = n_nationkey)")]
    ctes, shift = [], "0"
    for name, key, fk, features, table in blocks:
        cells = _list(f"{{'col': {i}, 'val': {e}}}" for i, e in enumerate(features.values()))
        ctes.append(f"{name}_dense AS (SELECT {key} AS k, unnest({cells}, recursive := true) FROM {table})")
        ctes.append(f"{name}_cells AS (SELECT k, {shift} + col AS col, val FROM {name}_dense WHERE val <> 0 UNION ALL SELECT {key}, {shift} + {len(features)} + row_number() OVER (ORDER BY {key}) - 1, 1.0 FROM {table})")
        shift = f"(SELECT {len(features)} + count(*) FROM part)"
    cells = "cells AS (SELECT l.r, x.col, x.val FROM l JOIN part_cells x ON l_partkey = x.k UNION ALL SELECT l.r, x.col, x.val FROM l JOIN supp_cells x ON l_suppkey = x.k)"
    sql = f"WITH l AS (SELECT row_number() OVER () AS r, l_partkey, l_suppkey FROM lineitem), {', '.join(ctes)}, {cells} SELECT a.col::BIGINT AS i, b.col::BIGINT AS j, sum(a.val * b.val) AS value FROM cells a JOIN cells b ON a.r = b.r AND a.col <= b.col GROUP BY ALL HAVING value <> 0"
    add("gram_long_k2z_keys", lambda s, d: with_keys(s, d).gram_long(), sql)


def _sweeps() -> None:
    """The sweeps over tuple ratio and join-domain size on the given tables."""
    k1 = FIXTURES["k1"]
    names = list(k1.features)
    cells = [(a, b) for i, a in enumerate(names) for b in names[i:]]
    for m in (1, 2, 5, 10, 15, 20):  # the sweep's parameter: line items kept of 30
        thin = Fixture(k1.build, k1.ids, k1.features, k1.tables + f" WHERE (7 * l_orderkey + 11 * l_suppkey + l_linenumber) % 30 < {m}")
        add(f"gram_thin{m}_k1", lambda s, d, m=m: upper(s, names, thinned(s, d, m).gram()), sql_pairs(thin, cells, lambda a, b: f"sum({a} * {b})"))
    for n_u in (10, 50, 100, 250, 500):
        own = emb(64, duck=True)
        cols = [f"a_{n}" for n in own] + [f"b_{n}" for n in own]
        side = lambda p: f"(SELECT vec_id % {n_u} AS j{p}, {_list(own.values())} AS {p} FROM embeddings)"  # noqa: B023, E731
        sql = f"WITH t AS (SELECT a || b AS x FROM {side('a')} JOIN {side('b')} ON ja = jb), n AS (SELECT {_list(repr(c) for c in cols)} AS names), p AS (SELECT unnest(range(1, {len(cols) + 1})) AS k) SELECT names[u.k] AS i, names[v.k] AS j, value FROM (SELECT p.k AS k, q.k AS l, sum(x[p.k] * x[q.k]) AS value FROM t, p, p q WHERE p.k <= q.k GROUP BY ALL) g JOIN p u ON g.k = u.k JOIN p v ON g.l = v.k, n"
        add(f"gram_self_join_{n_u}", lambda s, d, n=n_u, cols=cols: upper(s, cols, self_join(s, d, n).gram()), sql)
    for kind in ("min", "max"):
        word = {"min": "least", "max": "greatest"}[kind]
        add(f"col_{kind}_k1", lambda s, d, k=kind: vector(s, names, k1.build(s, d).col_extreme(k)), sql_vector(k1, lambda n, k=kind: f"{k}({n})"))
        add(f"row_{kind}_k1", lambda s, d, k=kind: keyed_rows(k1, k1.build(s, d).row_extreme(k)), f"WITH t AS ({k1.sql()}) SELECT {sql_ids(k1)}, {word}({', '.join(names)}) AS value FROM t")
    d2 = FIXTURES["d2"]
    add("col_sums_two_roles_d2", lambda s, d: vector(s, d2.features, d2.build(s, d).col_sums()), sql_vector(d2, lambda n: f"sum({n})"))


def _gd_sql(fx: Fixture, iters: int, residual: str, step: str) -> str:
    """Gradient rounds as a chain of one-row tables: w, gradient, next w."""
    names = list(fx.features)
    extra = "".join(f", {e} AS {n}" for n, e in TARGETS.items())
    parts = [f"t AS ({fx.sql(extra)})", f"w0 AS (SELECT {', '.join(f'0.0::DOUBLE AS w_{n}' for n in names)})"]
    score = " + ".join(f"w_{n} * {n}" for n in names)
    for i in range(iters):
        parts.append(f"g{i} AS (SELECT {', '.join(f'sum(r * {n}) AS g_{n}' for n in names)} FROM (SELECT t.*, {residual.format(s=score)} AS r FROM t, w{i}))")
        parts.append(f"w{i + 1} AS (SELECT {', '.join(f'w_{n} {step} * g_{n} AS w_{n}' for n in names)} FROM w{i}, g{i})")
    return "WITH " + ", ".join(parts) + f" SELECT unnest({_list(repr(n) for n in names)}) AS feature, unnest({_list(f'round(w_{n}, 6) + 0.0' for n in names)}) AS value FROM w{iters}"


def _kmeans_sql(fx: Fixture, names: list[str], c0: np.ndarray, iters: int) -> str:
    """Rounds for three centroids: distances, the nearest (the first on ties), means."""
    at = {n: i for i, n in enumerate(names)}
    parts = [f"t AS ({fx.sql()})", "c0 AS (SELECT " + ", ".join(f"{c0[i, j]}::DOUBLE AS c{i}_{j}" for i in at.values() for j in range(3)) + ")"]
    for it in range(iters):
        dist = [" + ".join(f"({n} - c{i}_{j}) * ({n} - c{i}_{j})" for n, i in at.items()) for j in range(3)]
        parts.append(f"a{it} AS (SELECT t.*, {', '.join(f'{x} AS d{j}' for j, x in enumerate(dist))} FROM t, c{it})")
        pick = ["d0 <= d1 AND d0 <= d2", "d1 < d0 AND d1 <= d2", "d2 < d0 AND d2 < d1"]
        parts.append(f"c{it + 1} AS (SELECT " + ", ".join(f"avg({n}) FILTER (WHERE {pick[j]}) AS c{i}_{j}" for n, i in at.items() for j in range(3)) + f" FROM a{it})")
    return "WITH " + ", ".join(parts) + f" SELECT unnest({_list(repr(n) for n in names for _ in range(3))}) AS feature, unnest({_list(str(j) for _ in names for j in range(3))})::INT AS cluster, unnest({_list(f'round(c{i}_{j}, 6)' for i in at.values() for j in range(3))}) AS value FROM c{iters}"


def _gnmf_sql(fx: Fixture, names: list[str], h0: np.ndarray, w0: list[str], iters: int) -> str:
    """Rounds of rank 2: the small factor from sums over rows, then the tall one row by row."""
    at = {n: i for i, n in enumerate(names)}
    parts = [f"t0 AS (SELECT *, CAST({w0[0]} AS DOUBLE) AS w0, CAST({w0[1]} AS DOUBLE) AS w1 FROM ({fx.sql()}))", "h0 AS (SELECT " + ", ".join(f"{h0[i, j]}::DOUBLE AS h{i}_{j}" for i in at.values() for j in range(2)) + ")"]
    for it in range(iters):
        parts.append(f"s{it} AS (SELECT sum(w0 * w0) AS g00, sum(w0 * w1) AS g01, sum(w1 * w1) AS g11, " + ", ".join(f"sum(w{j} * {n}) AS p{i}_{j}" for n, i in at.items() for j in range(2)) + f" FROM t{it})")
        den = lambda i, j: f"(h{i}_0 * g0{j} + h{i}_1 * g{'01' if j == 0 else '11'} + 1e-12)"
        parts.append(f"h{it + 1} AS (SELECT " + ", ".join(f"h{i}_{j} * p{i}_{j} / {den(i, j)} AS h{i}_{j}" for i in at.values() for j in range(2)) + f" FROM h{it}, s{it})")
        score = [" + ".join(f"{n} * h{i}_{j}" for n, i in at.items()) for j in range(2)]
        hh = lambda a, b: "(" + " + ".join(f"h{i}_{a} * h{i}_{b}" for i in at.values()) + ")"
        parts.append(f"t{it + 1} AS (SELECT t.* EXCLUDE (w0, w1), " + ", ".join(f"w{j} * ({score[j]}) / (w0 * {hh(0, j)} + w1 * {hh(1, j)} + 1e-12) AS w{j}" for j in range(2)) + f" FROM t{it} t, h{it + 1})")
    return "WITH " + ", ".join(parts) + f" SELECT unnest({_list(repr(n) for n in names for _ in range(2))}) AS feature, unnest({_list(str(j) for _ in names for j in range(2))})::INT AS component, unnest({_list(f'round(h{i}_{j}, 6)' for i in at.values() for j in range(2))}) AS value FROM h{iters}"


def _full_learning() -> None:
    """The four methods on two and three attribute tables with all their features, factored and joined."""
    a, b = 1e-5, 1e-7
    w0 = ["((7919 * l_orderkey) % 1000 + 1) / 1000.0", "((7919 * l_partkey + 104729) % 1000 + 1) / 1000.0"]
    for label, name in (("k2", "f2"), ("k2z", "f2z"), ("k3", "f3")):
        fx = FIXTURES[name]
        names = list(fx.features)
        c0 = np.array([[((7 * i + 13 * j) % 10) / 10 for j in range(3)] for i in range(len(names))])
        h0 = np.array([[((3 * i + 5 * j) % 9 + 1) / 10 for j in range(2)] for i in range(len(names))])
        for tail, rep in (("", lambda t: t), ("_m", lambda t: t.materialize())):
            add(f"logistic_gd_{label}{tail}", lambda s, d, fx=fx, rep=rep, names=names: vector(s, names, algos.logistic_gd(rep(fx.build(s, d)), "y", alpha=a, iters=3), 6), _gd_sql(fx, 3, "y / (1 + exp(y * ({s})))", f"+ {a}"))
            add(f"linreg_gd_{label}{tail}", lambda s, d, fx=fx, rep=rep, names=names: vector(s, names, algos.linreg_gd(rep(fx.build(s, d)), "q", alpha=b, iters=3), 6), _gd_sql(fx, 3, "({s}) - q", f"- {b}"))

            def kmeans(s, d, fx=fx, rep=rep, names=names, c0=c0):
                c, _ = algos.kmeans(rep(fx.build(s, d)), c0, 2)
                return s.createDataFrame([(n, j, round(float(c[i, j]), 6)) for i, n in enumerate(names) for j in range(3)], "feature string, cluster int, value double")

            def gnmf(s, d, fx=fx, rep=rep, names=names, h0=h0):
                _, h = algos.gnmf(rep(fx.build(s, d)), [F.expr(x) for x in w0], h0, 2)
                return s.createDataFrame([(n, j, round(float(h[i, j]), 6)) for i, n in enumerate(names) for j in range(2)], "feature string, component int, value double")

            if label != "k3":
                add(f"kmeans_{label}{tail}", kmeans, _kmeans_sql(fx, names, c0, 2))
                add(f"gnmf_{label}{tail}", gnmf, _gnmf_sql(fx, names, h0, w0, 2))


def _learning() -> None:
    fx = FIXTURES["g1"]
    names = list(fx.features)
    extra = "".join(f", {e} AS {n}" for n, e in TARGETS.items())
    a, b = 1e-5, 1e-6
    for label, rep in (("k1", lambda t: t), ("m", lambda t: t.materialize())):
        add(f"logistic_gd_{label}", lambda s, d, rep=rep: vector(s, names, algos.logistic_gd(rep(fx.build(s, d)), "y", alpha=a, iters=3), 6), _gd_sql(fx, 3, "y / (1 + exp(y * ({s})))", f"+ {a}"))
        add(f"linreg_gd_{label}", lambda s, d, rep=rep: vector(s, names, algos.linreg_gd(rep(fx.build(s, d)), "q", alpha=b, iters=3), 6), _gd_sql(fx, 3, "({s}) - q", f"- {b}"))
    add("logistic_as_printed_k1", lambda s, d: vector(s, names, algos.logistic_gd(fx.build(s, d), "y", alpha=a, iters=3, form="as_printed"), 6), _gd_sql(fx, 3, "y / (1 + exp({s}))", f"+ {a}"))
    add("linreg_cofactor_k1", lambda s, d: vector(s, names, algos.linreg_cofactor(fx.build(s, d), "q", alpha=b, iters=3), 6), _gd_sql(fx, 3, "({s}) - q", f"- {b}"))

    two = ["l_price", "p_sz"]
    small = f"WITH t AS ({fx.sql(extra)}), s AS (SELECT sum(l_price * l_price) AS a, sum(l_price * p_sz) AS b, sum(p_sz * p_sz) AS c, sum(l_price * q) AS u, sum(p_sz * q) AS v FROM t)"
    cramer = small + " SELECT unnest(['l_price', 'p_sz']) AS feature, unnest([round((u * c - v * b) / (a * c - b * b), 6), round((a * v - b * u) / (a * c - b * b), 6)]) AS value FROM s"
    add("linreg_normal_k1", lambda s, d: vector(s, two, algos.linreg_normal(fx.build(s, d)[two], "q"), 6), cramer)

    def solve(s, d):
        t = fx.build(s, d)[two]
        return vector(s, two, t.solve(t.row_matrix("q"))[:, 0], 6)

    add("solve_small_k1", solve, cramer)

    # K-Means on two scaled features and three starting centroids
    c0 = np.array([[0.1, 0.3, 0.6], [0.2, 0.9, 0.5]])
    parts = [f"t AS ({fx.sql()})", "c0 AS (SELECT " + ", ".join(f"{c0[i, j]}::DOUBLE AS c{i}{j}" for i in range(2) for j in range(3)) + ")"]
    for it in range(3):
        dist = [" + ".join(f"({n} - c{i}{j}) * ({n} - c{i}{j})" for i, n in enumerate(two)) for j in range(3)]
        parts.append(f"a{it} AS (SELECT t.*, {', '.join(f'{x} AS d{j}' for j, x in enumerate(dist))} FROM t, c{it})")
        pick = [f"d0 <= d1 AND d0 <= d2", "d1 < d0 AND d1 <= d2", "d2 < d0 AND d2 < d1"]
        parts.append(f"c{it + 1} AS (SELECT " + ", ".join(f"avg({n}) FILTER (WHERE {pick[j]}) AS c{i}{j}" for i, n in enumerate(two) for j in range(3)) + f" FROM a{it})")
    km = "WITH " + ", ".join(parts) + f" SELECT unnest({_list(repr(n) for n in two for _ in range(3))}) AS feature, unnest([0, 1, 2, 0, 1, 2])::INT AS cluster, unnest({_list(f'round(c{i}{j}, 6)' for i in range(2) for j in range(3))}) AS value FROM c3"

    def kmeans(s, d, rep=lambda t: t, ties="lowest"):
        c, _ = algos.kmeans(rep(fx.build(s, d)[two]), c0, 3, ties=ties)
        return s.createDataFrame([(n, j, round(float(c[i, j]), 6)) for i, n in enumerate(two) for j in range(3)], "feature string, cluster int, value double")

    add("kmeans_k1", kmeans, km)
    add("kmeans_m", lambda s, d: kmeans(s, d, lambda t: t.materialize()), km)
    add("kmeans_ties_all_k1", lambda s, d: kmeans(s, d, ties="all"), km)

    # GNMF of rank 2, two rounds; W starts from the keys
    gf = ["l_price", "l_disc", "p_sz"]
    h0 = np.array([[0.2, 0.7], [0.5, 0.1], [0.3, 0.4]])
    w0 = ["((7919 * l_orderkey + 104729 * 0) % 1000 + 1) / 1000.0", "((7919 * l_partkey + 104729) % 1000 + 1) / 1000.0"]

    def gnmf(s, d):
        t = fx.build(s, d)[gf]
        _, h = algos.gnmf(t, [F.expr(x) for x in w0], h0, 2)
        return s.createDataFrame([(n, j, round(float(h[i, j]), 6)) for i, n in enumerate(gf) for j in range(2)], "feature string, component int, value double")

    parts = [f"t0 AS (SELECT *, CAST({w0[0]} AS DOUBLE) AS w0, CAST({w0[1]} AS DOUBLE) AS w1 FROM ({fx.sql()}))", "h0 AS (SELECT " + ", ".join(f"{h0[i, j]}::DOUBLE AS h{i}{j}" for i in range(3) for j in range(2)) + ")"]
    for it in range(2):
        parts.append(f"s{it} AS (SELECT sum(w0 * w0) AS g00, sum(w0 * w1) AS g01, sum(w1 * w1) AS g11, " + ", ".join(f"sum(w{j} * {n}) AS p{i}{j}" for i, n in enumerate(gf) for j in range(2)) + f" FROM t{it})")
        den = lambda i, j: f"(h{i}0 * g0{j} + h{i}1 * g{'01' if j == 0 else '11'} + 1e-12)"
        parts.append(f"h{it + 1} AS (SELECT " + ", ".join(f"h{i}{j} * p{i}{j} / {den(i, j)} AS h{i}{j}" for i in range(3) for j in range(2)) + f" FROM h{it}, s{it})")
        sc = [" + ".join(f"{n} * h{i}{j}" for i, n in enumerate(gf)) for j in range(2)]
        hh = lambda a, b: "(" + " + ".join(f"h{i}{a} * h{i}{b}" for i in range(3)) + ")"
        parts.append(f"t{it + 1} AS (SELECT t.* EXCLUDE (w0, w1), " + ", ".join(f"w{j} * ({sc[j]}) / (w0 * {hh(0, j)} + w1 * {hh(1, j)} + 1e-12) AS w{j}" for j in range(2)) + f" FROM t{it} t, h{it + 1})")
    add("gnmf_k1", gnmf, "WITH " + ", ".join(parts) + f" SELECT unnest({_list(repr(n) for n in gf for _ in range(2))}) AS feature, unnest([0, 1, 0, 1, 0, 1])::INT AS component, unnest({_list(f'round(h{i}{j}, 6)' for i in range(3) for j in range(2))}) AS value FROM h2")

    _full_learning()

    w = np.array([1.0, -2.0, 0.5, 3.0, -1.0])
    score = " + ".join(f"({x}) * {n}" for x, n in zip(w, names))
    tcte = f"WITH t AS ({fx.sql(extra)})"
    add("predict_linear_k1", lambda s, d: keyed_rows(fx, algos.predict(fx.build(s, d), w)).withColumn("value", F.round("value", 9) + 0.0), f"{tcte} SELECT {sql_ids(fx)}, round({score}, 9) + 0.0 AS value FROM t")
    add("predict_logistic_k1", lambda s, d: keyed_rows(fx, algos.predict(fx.build(s, d), w, "logistic")).withColumn("value", F.round("value", 6)), f"{tcte} SELECT {sql_ids(fx)}, round(1 / (1 + exp(-({score}))), 6) AS value FROM t")
    add("loss_sse_k1", lambda s, d: s.createDataFrame([(round(algos.loss(fx.build(s, d), w, "q"), 3),)], "value double"), f"{tcte} SELECT round(sum((({score}) - q) * (({score}) - q)), 3) AS value FROM t")
    add("loss_log_k1", lambda s, d: s.createDataFrame([(round(algos.loss(fx.build(s, d), w, "y", "log"), 4),)], "value double"), f"{tcte} SELECT round(sum(ln(1 + exp(-y * ({score})))), 4) AS value FROM t")
    mn = FIXTURES["mn"]
    mnames = list(mn.features)
    y = "(CASE WHEN (c_custkey + s_suppkey) % 2 = 0 THEN 1.0 ELSE -1.0 END)"
    mparts = [f"t AS (SELECT *, CAST({y} AS DOUBLE) AS y FROM ({mn.sql()}))", f"w0 AS (SELECT {', '.join(f'0.0::DOUBLE AS w_{n}' for n in mnames)})"]
    mscore = " + ".join(f"w_{n} * {n}" for n in mnames)
    for i in range(2):
        mparts.append(f"g{i} AS (SELECT {', '.join(f'sum(r * {n}) AS g_{n}' for n in mnames)} FROM (SELECT t.*, y / (1 + exp(y * ({mscore}))) AS r FROM t, w{i}))")
        mparts.append(f"w{i + 1} AS (SELECT {', '.join(f'w_{n} + 1e-9 * g_{n} AS w_{n}' for n in mnames)} FROM w{i}, g{i})")

    def logistic_mn(s, d):
        t = mn.build(s, d)
        t = t.labelled("y", lambda a, b: 1.0 - 2.0 * ((a + b) % 2) * ((a + b) % 2))
        return vector(s, mnames, algos.logistic_gd(t, "y", alpha=1e-9, iters=2), 6)

    add("logistic_gd_mn", logistic_mn, "WITH " + ", ".join(mparts) + f" SELECT unnest({_list(repr(n) for n in mnames)}) AS feature, unnest({_list(f'round(w_{n}, 6) + 0.0' for n in mnames)}) AS value FROM w2")


def _measures() -> None:
    def ratios(s, d):
        rows = []
        for name in ("k1", "k1min", "k1o", "oc", "d1"):
            t = FIXTURES[name].build(s, d)
            st = t.trimmed(rows=False).stats()
            x = st["links"][0]
            rows.append((name, st["n"], x["targets"], round(x["tuple_ratio"], 6), round(x["feature_ratio"], 6), planner.should_factor(x["tuple_ratio"], x["feature_ratio"])))
        return s.createDataFrame(rows, "fixture string, n long, targets long, tuple_ratio double, feature_ratio double, factor boolean")

    one = lambda n, t, fk, de, da: f"SELECT '{n}' AS fixture, count(*) AS n, count(DISTINCT {fk}) AS targets, round(count(*) / count(DISTINCT {fk}), 6) AS tuple_ratio, round({da}::DOUBLE / {de}, 6) AS feature_ratio, count(*) / count(DISTINCT {fk}) >= 5 AND {da}::DOUBLE / {de} >= 1 AS factor FROM {t}"
    add("stats_ratios", ratios, " UNION ALL ".join([one("k1", "lineitem", "l_partkey", 4, 33), one("k1min", "lineitem", "l_partkey", 4, 2), one("k1o", "lineitem", "l_orderkey", 4, 9), one("oc", "orders", "o_custkey", 9, 36), one("d1", "events", "user_id", 7, 64)]))

    def cells(s, d):
        t = FIXTURES["k2"].build(s, d)
        b = t.cooc_bounds(0, 1)
        n = t.cooc(0, 1)
        r = n.agg(F.count("*").alias("nnz"), F.sum("_c").alias("n")).first()
        return s.createDataFrame([(b["low"], r["nnz"], b["high"], r["n"])], "low long, nnz long, high long, total long")

    add("cooc_nnz_bounds", cells, "SELECT greatest(count(DISTINCT l_partkey), count(DISTINCT l_suppkey)) AS low, (SELECT count(*) FROM (SELECT DISTINCT l_partkey, l_suppkey FROM lineitem)) AS nnz, count(*) AS high, count(*) AS total FROM lineitem")

    def counts(s, d):
        n, na = (s.read.parquet(f"{d}/{t}.parquet").count() for t in ("lineitem", "part"))
        dims = cost.Dims(n, 4, ((na, 33),))
        rows = [(op, float(cost.ops(op, dims, "M")), float(cost.ops(op, dims, "F"))) for op in ("scalar", "lmm", "gram")]
        return s.createDataFrame(rows, "op string, joined double, factored double")

    nn = "(SELECT count(*)::DOUBLE AS n FROM lineitem), (SELECT count(*)::DOUBLE AS a FROM part)"
    add("op_counts", counts, f"SELECT unnest(['scalar', 'lmm', 'gram']) AS op, unnest([n * 37, n * 37, 37 * 37 * n / 2]) AS joined, unnest([n * 4 + a * 33, n * 4 + a * 33, 16 * n / 2 + 33 * 33 * a / 2 + 4 * 33 * a]) AS factored FROM {nn}")

    def invertible(s, d):
        parts = s.read.parquet(f"{d}/lineitem.parquet").groupBy("l_linenumber").agg(F.count("*").alias("n"), F.count_distinct("l_partkey").alias("targets")).collect()  # a few line numbers
        rows = [(int(r["l_linenumber"]), r["n"] / r["targets"], fr, cost.invertible_possible(r["n"] / r["targets"], fr)) for r in parts for fr in (0.25, 0.5, 1.0, 2.0)]
        return s.createDataFrame(rows, "line int, tuple_ratio double, feature_ratio double, possible boolean")

    add("invertibility_bound", invertible, "SELECT l_linenumber::INT AS line, n::DOUBLE / targets AS tuple_ratio, fr::DOUBLE AS feature_ratio, n::DOUBLE / targets <= (1 / fr::DOUBLE + 1) * (1 + 1e-12) AS possible FROM (SELECT l_linenumber, count(*) AS n, count(DISTINCT l_partkey) AS targets FROM lineitem GROUP BY 1), (SELECT unnest([0.25, 0.5, 1, 2]) AS fr)")

    def plan(s, d):
        _, verdicts = planner.plan_star(FIXTURES["k3"].build(s, d))
        return s.createDataFrame(list(zip(["part", "supplier", "orders"], verdicts)), "block string, factor boolean")

    add("decision_rule_k3", plan, "SELECT 'part' AS block, count(*) / (SELECT count(*) FROM part) >= 5 AS factor FROM lineitem UNION ALL SELECT 'supplier', count(*) / (SELECT count(*) FROM supplier) >= 5 FROM lineitem UNION ALL SELECT 'orders', count(*) / (SELECT count(*) FROM orders) >= 5 AND 1 <= 1 FROM lineitem".replace("AND 1 <= 1", "AND 9 >= 9"))


_linear_algebra()
_wide_sparse()
_sweeps()
_learning()
_measures()
