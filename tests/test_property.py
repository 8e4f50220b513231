"""Random small stars: duplicates, unused and missing targets, no entity features, one feature, few rows."""

import random

import numpy as np
import pytest

from foldstar import cost
from foldstar.normalized import FactoredMatrix


def star(spark, seed):
    r = random.Random(seed)
    q, d_e = r.randint(1, 3), r.choice([0, 1, 3])
    sizes = [(r.randint(1, 5), r.randint(1, 3)) for _ in range(q)]
    n = r.choice([1, 2, 5, 12])
    rows = []
    for i in range(n):
        rows.append((i, *[r.choice([*range(k), None, 99]) if r.random() < 0.3 else r.randrange(k) for k, _ in sizes], *[float(r.randint(-3, 3)) for _ in range(d_e)]))
    e = spark.createDataFrame(rows, "id long, " + ", ".join(f"k{j} long" for j in range(q)) + "".join(f", e{j} double" for j in range(d_e)))
    blocks = []
    for j, (k, w) in enumerate(sizes):
        names = [f"a{j}_{c}" for c in range(w)]
        df = spark.createDataFrame([(t, *[float(r.randint(-3, 3)) for _ in names]) for t in range(k)], "id long, " + ", ".join(f"{c} double" for c in names))
        blocks.append((df, f"k{j}", "id", names))
    return FactoredMatrix.star(e, blocks, [f"e{j}" for j in range(d_e)], ["id"])


@pytest.mark.parametrize("seed", range(6))
def test_factored_equals_joined(spark, seed):
    t = star(spark, seed)
    T = t.materialize().collect()
    T = T.reshape(len(T), t.d)
    assert t.n_rows() == len(T)
    assert (t.gram() == T.T @ T).all() and (t.gram(pairs="cooc") == T.T @ T).all()
    assert (t.col_sums() == T.sum(axis=0)).all() and t.sum() == T.sum()
    got = sorted(map(tuple, (t @ np.arange(1.0, t.d + 1)).frame.select("id", "_v0").collect()))
    want = sorted(map(tuple, t.materialize().scored(np.arange(1.0, t.d + 1).reshape(-1, 1)).frame.select("id", "_v0").collect()))
    assert got == want
    if len(T):
        assert sorted(r[0] for r in t.row_extreme("max").frame.select("_v0").collect()) == sorted(T.max(axis=1))
        assert (t.col_extreme("min") == T.min(axis=0)).all()


def test_all_ones_by_all_distinct(spark):
    """Nothing is redundant in T op X when X is distinct everywhere, however redundant T is."""
    e = spark.createDataFrame([(i, 0, 1.0) for i in range(4)], "id long, k long, e double")
    a = spark.createDataFrame([(0, 1.0)], "k long, a double")
    t = FactoredMatrix.star(e, [(a, "k", "k", ["a"])], ["e"], ["id"])
    x = spark.createDataFrame([(i, float(2 * i), float(2 * i + 1)) for i in range(4)], "id long, e double, a double")
    got = sorted(map(tuple, t.elementwise(x, "id", lambda p, q: p * q).collect()))
    assert len({v for r in got for v in r[1:]}) == 8


@pytest.mark.parametrize("seed", range(4))
def test_no_square_inverse_beyond_the_bound(seed):
    g = np.random.default_rng(seed)
    for _ in range(50):
        n_a, d_e, d_a = g.integers(1, 5), g.integers(0, 4), g.integers(1, 5)
        n = d_e + d_a
        e, a = g.normal(size=(n, d_e)), g.normal(size=(n_a, d_a))
        k = np.concatenate([np.arange(n_a), g.integers(0, n_a, size=max(n - n_a, 0))])[:n]
        if len(set(k)) < n_a:
            continue
        T = np.hstack([e, a[k]])
        fr = d_a / d_e if d_e else float("inf")
        if not cost.invertible_possible(n / n_a, fr):
            assert np.linalg.matrix_rank(T) < n
