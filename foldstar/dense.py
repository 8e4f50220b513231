"""Products of column sets of one frame, returned as small arrays."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Up to so many products of row values run as SQL sums: more make one generated method too long to be compiled.
SQL_PRODUCTS = 36
#: The same for sums over one row a target, where planning is what counts.
TARGET_PRODUCTS = 160
#: A d x d result is kept on the driver up to this width; every partition sends at most its cells.
MAX_WIDTH = 2_000


def d(c) -> Column:
    return (F.col(f"`{c}`") if isinstance(c, str) else c).cast("double")


def sums(frame: DataFrame, columns: list) -> np.ndarray:
    """Sums of column expressions: one aggregate, one row to the driver."""
    if not columns:
        return np.zeros(0)
    row = frame.agg(*[F.coalesce(F.sum(d(c)), F.lit(0.0)).alias(f"s{i}") for i, c in enumerate(columns)]).first()
    return np.array(row, dtype=float)


def flat(frame: DataFrame, columns: list, partial, size: int) -> DataFrame:
    """Rows (p, v): `size` numbers that partial(rows as an array) gives for each batch, added up in each partition."""

    def run(frames):
        total = np.zeros(size)
        for f in frames:
            total += partial(f.to_numpy(dtype=float))
        hit = np.flatnonzero(total)
        yield pd.DataFrame({"p": hit, "v": total[hit]})

    return frame.select(*[d(c).alias(f"c{i}") for i, c in enumerate(columns)]).mapInPandas(run, "p long, v double")


def listed(frame: DataFrame, columns: list, places: list[int]) -> DataFrame:
    """Rows (p, v): the sum of columns[i] at places[i], by one aggregate."""
    got = frame.agg(*[F.coalesce(F.sum(d(c)), F.lit(0.0)).alias(f"s{i}") for i, c in enumerate(columns)])
    cells = F.explode(F.array(*[F.struct(F.lit(p).cast("long").alias("p"), F.col(f"s{i}").alias("v")) for i, p in enumerate(places)]))
    return got.select(cells.alias("x")).select("x.p", "x.v")


def gathered(pieces: list[tuple[DataFrame, int]]) -> list[np.ndarray]:
    """Several (p, v) frames of so many numbers each, added up by position in one query."""
    if not pieces:
        return []
    both = None
    for t, (f, _) in enumerate(pieces):
        f = f.select(F.lit(t).alias("t"), "p", "v")
        both = f if both is None else both.unionByName(f)
    got = both.groupBy("t", "p").agg(F.sum("v").alias("v")).toPandas()
    out = [np.zeros(size) for _, size in pieces]
    for t, part in got.groupby("t"):
        out[t][part["p"].to_numpy(dtype=int)] = part["v"]
    return out


def mirrored(upper: np.ndarray) -> np.ndarray:
    """A symmetric matrix from its upper half."""
    return np.triu(upper) + np.triu(upper, 1).T


def product_cells(frame: DataFrame, left: list[str], right: list[str] | None = None, weight: str | None = None, lane: str = "auto") -> DataFrame:
    """left^T diag(weight) right over the rows of `frame` as rows (p, v) with p = i * len(right) + j; `right` None: left with itself, upper half only.

    Lane "sql": sums in generated code. Lane "arrow": one BLAS product per batch, added up per
    partition, then by position; only len(left) * len(right) numbers per partition are shuffled.
    """
    own = right is None
    right = left if own else right
    a, b = len(left), len(right)
    if max(a, b) > MAX_WIDTH:
        raise ValueError(f"a product of width {max(a, b)} is too large for the driver; use the long form")
    if lane == "sql" or lane == "auto" and a * b <= SQL_PRODUCTS:
        cells = [(i, j) for i in range(a) for j in range(i if own else 0, b)]
        w = d(weight) if weight else None
        return listed(frame, [w * d(left[i]) * d(right[j]) if weight else d(left[i]) * d(right[j]) for i, j in cells], [i * b + j for i, j in cells])
    names = list(dict.fromkeys([*left, *right, *([weight] if weight else [])]))
    at = {n: i for i, n in enumerate(names)}
    li, ri, wi = [at[n] for n in left], [at[n] for n in right], at[weight] if weight else None

    def partial(x):
        l = x[:, li] if wi is None else x[:, li] * x[:, [wi]]
        return (np.triu(l.T @ x[:, ri]) if own else l.T @ x[:, ri]).ravel()

    return flat(frame, names, partial, a * b)


def products(frame: DataFrame, left: list[str], right: list[str] | None = None, weight: str | None = None, lane: str = "auto") -> np.ndarray:
    """`product_cells` as a small array."""
    a, b = len(left), len(left if right is None else right)
    if not a or not b:
        return np.zeros((a, b))
    out = gathered([(product_cells(frame, left, right, weight, lane), a * b)])[0].reshape(a, b)
    return mirrored(out) if right is None else out


def pinv(g: np.ndarray) -> np.ndarray:
    """Pseudo-inverse of a symmetric matrix, cut off at width * eps * largest singular value."""
    w, v = np.linalg.eigh((g + g.T) / 2)
    keep = np.abs(w) > max(g.shape[0], 1) * np.finfo(float).eps * np.abs(w).max(initial=0)
    return (v[:, keep] / w[keep]) @ v[:, keep].T
