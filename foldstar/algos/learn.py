"""Logistic and linear regression, K-Means, Gaussian non-negative matrix factorization.

Weights, centroids and factors of d rows live on the driver; everything with n rows stays beside the
row frame. An iteration is one scoring and one folding of T.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from foldstar.dense import pinv
from foldstar.lineage import cut


def logistic_gd(t, y: str, w0=None, alpha: float = 1e-3, iters: int = 20, form: str = "margin") -> np.ndarray:
    """Gradient ascent on the log-likelihood for labels -1 and 1.

    form="margin" uses y / (1 + exp(y s)), the gradient of the log-likelihood; form="as_printed"
    leaves y out of the exponent.
    """
    w = np.zeros(t.d) if w0 is None else np.asarray(w0, dtype=float)
    for _ in range(iters):
        w = w + alpha * t.folded_scores(w, y, lambda s, target, exp: target / (1 + exp((target if form == "margin" else 1) * s)))
    return w


def linreg_normal(t, y: str) -> np.ndarray:
    """Least squares through the Gram matrix and its pseudo-inverse: one pass over T."""
    return pinv(t.gram()) @ (t.T @ t.row_matrix(y))[:, 0]


def linreg_gd(t, y: str, w0=None, alpha: float = 1e-3, iters: int = 20) -> np.ndarray:
    w = np.zeros(t.d) if w0 is None else np.asarray(w0, dtype=float)
    for _ in range(iters):
        r = (t @ w).apply(lambda v: [v[0] - F.col(y).cast("double")])
        w = w - alpha * (t.T @ r)[:, 0]
    return w


def linreg_cofactor(t, y: str, w0=None, alpha: float = 1e-3, iters: int = 20, step: str = "constant", eps: float = 1e-8) -> np.ndarray:
    """Gram and T^T y once, then gradient steps in d dimensions; step="adagrad" adapts each coordinate's rate."""
    g, c = t.gram(), (t.T @ t.row_matrix(y))[:, 0]
    w = np.zeros(t.d) if w0 is None else np.asarray(w0, dtype=float)
    seen = np.zeros(t.d)
    for _ in range(iters):
        grad = g @ w - c
        seen += grad * grad
        w = w - (alpha * grad / (np.sqrt(seen) + eps) if step == "adagrad" else alpha * grad)
    return w


def linreg(t, y: str, method: str = "auto", max_width: int = 5000, **how) -> np.ndarray:
    """Normal equations while the Gram is affordable, gradient descent beyond."""
    if method == "gd" or method == "auto" and t.d > max_width:
        return linreg_gd(t, y, **how)
    return linreg_normal(t, y)


def kmeans(t, c0: np.ndarray, iters: int = 20, ties: str = "lowest", empty: str = "keep") -> tuple[np.ndarray, object]:
    """Centroids (d x k) and the n x k assignment, from starting centroids c0 (d x k).

    Squared distances are row norms plus centroid norms minus twice the scores. ties="all" gives a
    row to each nearest centroid, "lowest" to the first; a centroid without rows stays or becomes NaN.
    """
    c = np.asarray(c0, dtype=float)
    k = c.shape[1]
    here = t.with_row_sums("_norm", lambda x: x * x)
    assigned = None
    for _ in range(iters):
        scores = here @ (2 * np.nan_to_num(c))
        own = (np.nan_to_num(c) ** 2).sum(axis=0)

        def near(v, own=own):
            dist = [F.col("_norm") + F.lit(float(n)) - s for n, s in zip(own, v)]
            low = F.least(*dist) if k > 1 else dist[0]
            if ties == "all":
                return [(x == low).cast("double") for x in dist]
            first = F.array_position(F.array(*dist), low)
            return [(first == j + 1).cast("double") for j in range(k)]

        assigned = scores.apply(near)
        sums, counts = here.folded(assigned, assigned.cols)
        with np.errstate(invalid="ignore", divide="ignore"):
            new = sums / counts
        c = np.where(counts > 0, new, c if empty == "keep" else np.nan)
    return c, assigned


def gnmf(t, w0: list, h0: np.ndarray, iters: int = 20, eps: float = 1e-12, save=None):
    """Multiplicative updates for T about W H^T. w0: r column expressions of the row frame; h0: d x r.

    W lives beside the rows. `save(frame)` writes a frame and reads it again, so that lineage ends with
    each iteration (default: lineage.cut); only the columns of the row frame and W are written.
    """
    save = save or cut
    h = np.asarray(h0, dtype=float)
    if h.min(initial=0) < 0:
        raise ValueError("factors must not be negative")
    r = h.shape[1]
    from foldstar.matrix import RowMatrix

    frame = t.row_frame().select("*", *[c.cast("double").alias(f"_w{j}") for j, c in enumerate(w0)])
    cols = [f"_w{j}" for j in range(r)]
    here = t.on(frame)
    for _ in range(iters):
        w = RowMatrix(here.row_frame(), cols, here)
        pairs = [(i, j) for i in range(r) for j in range(i, r)]
        tw, ww = here.folded(w, [F.col(cols[i]) * F.col(cols[j]) for i, j in pairs])
        g = np.zeros((r, r))
        for (i, j), v in zip(pairs, ww):
            g[i, j] = g[j, i] = v
        h = h * tw / (h @ g + eps)
        hh = h.T @ h
        scores = here @ h

        def step(v, hh=hh):
            old = [F.col(c) for c in cols]
            return [o * s / (sum((o2 * F.lit(float(hh[i, j])) for i, o2 in enumerate(old)), F.lit(0.0)) + F.lit(eps)) for j, (o, s) in enumerate(zip(old, v))]

        new = scores.apply(step)
        frame = new.frame.drop(*cols).withColumnsRenamed(dict(zip(new.cols, cols)))
        frame = save(frame)
        here = here.on(frame)
    return RowMatrix(here.row_frame(), cols, here), h


def predict(t, w: np.ndarray, kind: str = "linear"):
    """n x m predictions: T w, its sigmoid, or for "centroid" the index of the nearest column of w."""
    if kind == "linear":
        return t @ w
    if kind == "logistic":
        return (t @ w).apply(lambda v: [1 / (1 + F.exp(-c)) for c in v])
    own = (np.asarray(w) ** 2).sum(axis=0)
    return (t @ w).apply(lambda v: [(F.array_position(F.array(*[F.lit(float(n)) - 2 * c for n, c in zip(own, v)]), F.array_min(F.array(*[F.lit(float(n)) - 2 * c for n, c in zip(own, v)]))) - 1)])


def loss(t, w, y: str | None = None, kind: str = "sse") -> float:
    """sse and log-loss against a row column; inertia of centroids (d x k)."""
    if kind == "sse":
        return float((t @ w).apply(lambda v: [(v[0] - F.col(y)) * (v[0] - F.col(y))]).col_sums()[0])
    if kind == "log":
        return float((t @ w).apply(lambda v: [F.log1p(F.exp(-F.col(y) * v[0]))]).col_sums()[0])
    own = (np.asarray(w) ** 2).sum(axis=0)
    low = (t @ w).apply(lambda v: [F.array_min(F.array(*[F.lit(float(n)) - 2 * c for n, c in zip(own, v)]))]).col_sums()[0]
    return float(low + (t**2).sum())
