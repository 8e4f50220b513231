"""The experiment sweeps: each returns rows of parameters, seconds joined (M) and factored (F), and predictions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from foldstar import algos, baselines, cost, measures, planner, synth
from foldstar.keyed import KeyedJoin
from foldstar.normalized import FactoredMatrix

OPERATORS = {
    "scalar": lambda t: (3 * t).sum(),
    "row_sums": lambda t: t.row_sums().col_sums(),
    "col_sums": lambda t: t.col_sums(),
    "sum": lambda t: t.sum(),
    "lmm": lambda t: (t @ np.ones((t.d, 2))).col_sums(),
    "rmm": lambda t: t.T @ t.row_matrix("id"),
    "gram": lambda t: t.gram(),
    "ginv": lambda t: t.ginv() @ t.row_matrix("id"),
}


def _pair(spark, n_e, d_e, blocks):
    t = synth.key_join(spark, n_e, d_e, blocks)
    t.rows.persist().count()
    for k in t.links:
        k.block.df.persist().count()
    m = t.materialize().cache()
    return t, m


def _free(t, m):
    m.frame.unpersist()
    t.rows.unpersist()
    for k in t.links:
        k.block.df.unpersist()


def key_join_sweep(spark: SparkSession, n_a: int, d_e: int, grid: list[tuple[int, float]], ops=("lmm", "gram"), reps: int = 2) -> list[dict]:
    """grid of (tuple ratio, feature ratio): operators on a synthetic key join."""
    out = []
    for tr, fr in grid:
        d_a = max(1, round(fr * d_e))
        t, m = _pair(spark, tr * n_a, d_e, [(n_a, d_a)])
        dims = cost.Dims(tr * n_a, d_e, ((n_a, d_a),))
        for op in ops:
            r = measures.compare_times(OPERATORS[op], m, t, reps=reps)
            known = {"scalar": "scalar", "row_sums": "aggregate", "col_sums": "aggregate", "sum": "aggregate"}.get(op, op)
            out.append({"op": op, "tuple_ratio": tr, "feature_ratio": fr, **r, "predicted": cost.speedup(known, dims), "factor": planner.should_factor(tr, fr)})
        _free(t, m)
    return out


def algorithm_sweep(spark: SparkSession, n_a: int, d_e: int, grid: list[tuple[int, float]], iters: int = 5, k: int = 5) -> list[dict]:
    """Logistic regression, least squares, K-Means and GNMF, joined against factored."""
    out = []
    for tr, fr in grid:
        d_a = max(1, round(fr * d_e))
        t, m = _pair(spark, tr * n_a, d_e, [(n_a, d_a)])
        runs = {
            "logistic": lambda a: algos.logistic_gd(a, "y", alpha=1e-6, iters=iters),
            "linreg_normal": lambda a: algos.linreg_normal(a, "y"),
            "linreg_gd": lambda a: algos.linreg_gd(a, "y", alpha=1e-9, iters=iters),
            "linreg_cofactor": lambda a: algos.linreg_cofactor(a, "y", alpha=1e-9, iters=iters),
            "kmeans": lambda a: algos.kmeans(a, np.arange(a.d * k).reshape(a.d, k) % 7 + 0.5, iters),
            "gnmf": lambda a: algos.gnmf(a, [F.lit(0.5) + F.col("id") % (j + 2) for j in range(3)], np.ones((a.d, 3)), 2),
        }
        for name, fn in runs.items():
            r = measures.compare_times(fn, m, t, warmup=0, reps=1)
            out.append({"algorithm": name, "tuple_ratio": tr, "feature_ratio": fr, **r})
        _free(t, m)
    return out


def many_to_many_sweep(spark: SparkSession, n: int, d: int, domains: list[int], with_pairs: bool = True) -> list[dict]:
    """Gram of an M:N join for several domain sizes: joined, by pair index, and keyed."""
    out = []
    for n_u in domains:
        a, b = synth.many_to_many(spark, n, d, n_u)
        a, b = a.persist(), b.persist()
        a.count(), b.count()
        keyed = KeyedJoin([(a, [f"a{j}" for j in range(d)]), (b, [f"b{j}" for j in range(d)])], [("j", "j")])
        row = {"uniqueness": n_u / n, "seconds_keyed": measures.measure(keyed.gram, 1, 1)["median"]}
        if with_pairs:
            t = FactoredMatrix.mn(synth.wide(a, "a", d), synth.wide(b, "b", d), a.select("id", "j"), b.select("id", "j")).explicit()
            row["seconds_f"] = measures.measure(t.gram, 0, 1)["median"]
            row["seconds_m"] = measures.measure(lambda t=t: t.materialize().gram(), 0, 1)["median"]
            row["speedup"] = row["seconds_m"] / row["seconds_keyed"]
        out.append(row)
        a.unpersist(), b.unpersist()
    return out


def specific_tool(spark: SparkSession, n_a: int, tr: int, d_e: int, ratios=(1, 2, 3, 4), iters: int = 5) -> list[dict]:
    """Logistic regression: joined, hash-probing tool for one key join, and the framework."""
    out = []
    for fr in ratios:
        t, m = _pair(spark, tr * n_a, d_e, [(n_a, fr * d_e)])
        k = t.links[0]
        row = {"feature_ratio": fr, **measures.compare_times(lambda a: algos.logistic_gd(a, "y", alpha=1e-6, iters=iters), m, t, warmup=0, reps=1)}
        row["seconds_tool"] = measures.measure(lambda: baselines.hash_glm(t.rows, t.own, k.column, k.block.df, "id", k.block.names, "y", 1e-6, iters), 0, 1)["median"]  # noqa: B023
        out.append(row)
        _free(t, m)
    return out


def preparation(spark: SparkSession, sf_dir: str, name: str = "k2", iters: int = 5) -> dict:
    """Seconds to prepare (join, or nothing but links) against seconds to learn, for both."""
    from foldstar.workloads import FIXTURES

    t = FIXTURES[name].build(spark, sf_dir)
    t = t.on(t.rows.withColumn("y", F.lit(1.0)))
    m = t.materialize()
    learn = lambda a: algos.logistic_gd(a, "y", alpha=1e-12, iters=iters)
    out = {"m": measures.prep_report(m.cache, lambda: learn(m))}
    m.frame.unpersist()
    out["f"] = measures.prep_report(lambda: t.rows.persist().count(), lambda: learn(t))
    t.rows.unpersist()
    return out


def rule_quality(rows: list[dict]) -> dict:
    """The decision rule and tuned thresholds over rows of key_join_sweep."""
    runs = [planner.Run(r["tuple_ratio"], r["feature_ratio"], r["seconds_m"], r["seconds_f"]) for r in rows]
    return {"fixed": planner.judge_rule(runs), "tuned": planner.tune_rule(runs)}
