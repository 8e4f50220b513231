"""What algorithms may call: a Matrix with n distributed rows, and n x m values beside those rows."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from foldstar import dense

#: Named scalar functions; those that map 0 to 0 keep sparse blocks sparse.
FUNCTIONS = {
    "log": F.log, "exp": F.exp, "sin": F.sin, "cos": F.cos, "tanh": F.tanh, "sqrt": F.sqrt, "abs": F.abs, "sign": F.signum,
    "round": F.round, "floor": F.floor, "ceil": F.ceil, "sigmoid": lambda c: 1 / (1 + F.exp(-c)), "square": lambda c: c * c,
}
#: Rows that may come to the driver: those of a right factor, or of a matrix with no more rows than columns.
SHORT_ROWS = 10_000
ZERO_STAYS = {"sin", "tanh", "sqrt", "abs", "sign", "round", "floor", "ceil", "square"}


def divided(a, b):
    """a / b with IEEE results for zero divisors (ANSI mode would raise)."""
    a, b = F.lit(a) if not isinstance(a, Column) else a, F.lit(b) if not isinstance(b, Column) else b
    inf = F.when(a > 0, float("inf")).when(a < 0, float("-inf")).otherwise(float("nan"))
    return F.when(b == 0, inf).otherwise(F.try_divide(a, b))


class RowMatrix:
    """n x m values as columns of a frame that still has the row space's own columns."""

    def __init__(self, frame: DataFrame, cols: list[str], space: object):
        self.frame, self.cols, self.space = frame, cols, space

    @property
    def m(self) -> int:
        return len(self.cols)

    def apply(self, f) -> RowMatrix:
        """f(list of value Columns) -> list of Columns, row by row; other columns of the row may be used by name."""
        made = f([F.col(c) for c in self.cols])
        keep = [c for c in self.frame.columns if c not in self.cols]
        names = [f"_v{i}" for i in range(len(made))]
        return RowMatrix(self.frame.select(*[F.col(f"`{c}`") for c in keep if c not in names], *[c.cast("double").alias(n) for c, n in zip(made, names)]), names, self.space)

    def __add__(self, x):
        return self.apply(lambda v: [c + x for c in v])

    def __mul__(self, x):
        return self.apply(lambda v: [c * x for c in v])

    __radd__, __rmul__ = __add__, __mul__

    def __sub__(self, x):
        return self.apply(lambda v: [c - x for c in v])

    def row_min(self) -> RowMatrix:
        return self.apply(lambda v: [v[0] if len(v) == 1 else F.least(*v)])

    def col_sums(self) -> np.ndarray:
        return dense.sums(self.frame, self.cols)

    def gram(self) -> np.ndarray:
        return dense.products(self.frame, self.cols)

    @property
    def T(self) -> Flipped:  # noqa: N802
        return Flipped(self)

    def persist(self) -> RowMatrix:
        self.frame.persist()
        return self

    def unpersist(self) -> None:
        self.frame.unpersist()


class Flipped:
    """The m x n transpose of n x m values: a flag, the values stay beside their rows."""

    def __init__(self, of: RowMatrix):
        self.of = of

    @property
    def T(self) -> RowMatrix:  # noqa: N802
        return self.of

    def __matmul__(self, t: Matrix) -> np.ndarray:
        return t.folded(self.of).T


class Matrix:
    """Operator overloads shared by the joined and the factored representation.

    Subclasses give `mapped`, `row_sums`, `col_sums`, `sum`, `scored` (T X), `folded` (T^T R), `gram`,
    `names` and `n_rows`. Element-wise operators are closed; the transpose is a flag on a wrapper.
    """

    names: list[str]
    __array_ufunc__ = None  # numpy leaves its operators to the ones below

    @property
    def d(self) -> int:
        return len(self.names)

    # element-wise with scalars
    def map(self, f, *args, keeps_zero: bool | None = None):
        if isinstance(f, str):
            keeps_zero = f in ZERO_STAYS if keeps_zero is None else keeps_zero
            g = F.pow if f == "pow" else FUNCTIONS[f]
        else:
            g = f
        return self.mapped(lambda c: g(c, *args), bool(keeps_zero))

    def exp(self):
        return self.map("exp")

    def __add__(self, x):
        if isinstance(x, Matrix):
            return self.plus(x)
        return self.mapped(lambda c: c + F.lit(x), x == 0)

    __radd__ = __add__

    def __sub__(self, x):
        if isinstance(x, Matrix):
            return self.plus(-1 * x)
        return self.mapped(lambda c: c - F.lit(x), x == 0)

    def __rsub__(self, x):
        return self.mapped(lambda c: F.lit(x) - c, x == 0)

    def __mul__(self, x):
        return self.mapped(lambda c: c * F.lit(x), True)

    __rmul__ = __mul__

    def __truediv__(self, x):
        return self.mapped(lambda c: divided(c, float(x)), x != 0)

    def __rtruediv__(self, x):
        return self.mapped(lambda c: divided(float(x), c), False)

    def __pow__(self, x):
        return self.mapped((lambda c: c * c) if x == 2 else (lambda c: F.pow(c, F.lit(float(x)))), x > 0)

    def __rpow__(self, x):
        return self.mapped(lambda c: F.pow(F.lit(float(x)), c), False)

    def __mod__(self, x):
        return self.mapped(lambda c: F.pmod(c, F.lit(float(x))), True)

    def __gt__(self, x):
        return self.mapped(lambda c: (c > F.lit(x)).cast("double"), x >= 0)

    def clip(self, lo: float, hi: float):
        return self.mapped(lambda c: F.least(F.greatest(c, F.lit(float(lo))), F.lit(float(hi))), lo <= 0 <= hi)

    # products
    def __matmul__(self, x):
        if isinstance(x, (Matrix, Transposed)):
            from foldstar.double import product

            return product(self, x)
        return self.scored(_columns(x, self.d))

    def __rmatmul__(self, x) -> np.ndarray:
        """X T as m x d: for n x m values in this matrix's row space X is their transpose; an array X (m x n) needs `_row`."""
        if isinstance(x, RowMatrix):
            return self.folded(x).T
        x = np.atleast_2d(np.asarray(x, dtype=float))
        if x.shape[1] > SHORT_ROWS:
            raise ValueError(f"an array of {x.shape[1]} columns; give longer ones as values beside the rows")
        frame, names = self.row_frame(), [f"_v{i}" for i in range(x.shape[0])]
        made = frame.sparkSession.createDataFrame([(i, *map(float, c)) for i, c in enumerate(x.T)], "_at long, " + ", ".join(f"{n} double" for n in names))
        return self.folded(RowMatrix(frame.join(made, F.col("_row") == F.col("_at")).drop("_at"), names, self)).T

    def folded_scores(self, w: np.ndarray, y: str, residual) -> np.ndarray:
        """T^T r for the row values r = residual(T w, y, exp), where y is a row column and exp that of Columns or of arrays."""
        target = F.col(y).cast("double")
        return (self.T @ (self @ w).apply(lambda v: [residual(v[0], target, F.exp)]))[:, 0]

    @property
    def T(self):  # noqa: N802
        return Transposed(self)

    # derived measures
    def col_means(self) -> np.ndarray:
        return self.col_sums() / max(self.n_rows(), 1)

    def col_var(self) -> np.ndarray:
        """Population variances from the sums of T and of T squared."""
        n = max(self.n_rows(), 1)
        return (self**2).col_sums() / n - (self.col_sums() / n) ** 2

    def cov(self) -> np.ndarray:
        n, s = self.n_rows(), self.col_sums()
        return (self.gram() - np.outer(s, s) / n) / (n - 1)

    def corr(self) -> np.ndarray:
        c = self.cov()
        s = np.sqrt(np.diag(c))
        with np.errstate(invalid="ignore", divide="ignore"):
            return c / np.outer(s, s)

    def pca(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        w, v = np.linalg.eigh(self.cov())
        return w[::-1][:k], v[:, ::-1][:, :k]

    def ginv(self) -> PseudoInverse | RowPseudoInverse:
        """Pseudo-inverse as factors of the smaller side: (T P)^T with P = pinv(T^T T) for d < n, T^T pinv(T T^T) for n <= d.

        The second needs rows numbered by `_row`; n is at most SHORT_ROWS there.
        """
        if self.n_rows() <= min(self.d, SHORT_ROWS) and "_row" in self.row_frame().columns:
            return RowPseudoInverse(self)
        return PseudoInverse(self, dense.pinv(self.gram()))

    def solve(self, b: RowMatrix) -> np.ndarray:
        """Least squares by the normal equations; a rank-deficient Gram gives the least-norm answer."""
        g, r = self.gram(), self.folded(b)
        try:
            c = np.linalg.cholesky(g)
            if np.diag(c).min() > 1e-7 * np.diag(c).max():
                return np.linalg.solve(g, r)
        except np.linalg.LinAlgError:
            pass
        return dense.pinv(g) @ r

    def cholesky_gram(self) -> np.ndarray:
        return np.linalg.cholesky(self.gram())

    def svd_gram(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Largest singular values and right singular vectors, from the Gram alone."""
        w, v = np.linalg.eigh(self.gram())
        return np.sqrt(np.maximum(w[::-1][:k], 0)), v[:, ::-1][:, :k]


class Transposed:
    """T^T: every operator is handed to T with rows and columns swapped; no data moves."""

    def __init__(self, of: Matrix):
        self.of = of

    @property
    def T(self) -> Matrix:  # noqa: N802
        return self.of

    def __matmul__(self, x):
        if isinstance(x, RowMatrix):
            return self.of.folded(x)
        from foldstar.double import product

        return product(self, x)

    def map(self, f, *args, **kw):
        return Transposed(self.of.map(f, *args, **kw))

    def row_sums(self) -> np.ndarray:
        return self.of.col_sums()

    def col_sums(self) -> RowMatrix:
        return self.of.row_sums()

    def sum(self) -> float:
        return self.of.sum()

    def __rmatmul__(self, x) -> Flipped:
        """X T^T for an m x d array X: the transpose of T X^T, whose values stay beside T's rows."""
        return Flipped(self.of @ np.atleast_2d(np.asarray(x, dtype=float)).T)

    __array_ufunc__ = None

    def gram(self, on: str = "_row", max_rows: int = 5000) -> DataFrame:
        """T T^T in long form (r, s, value), r <= s by the row id `on`: quadratic in rows, by blocks of rows beyond max_rows."""
        return self.of.kernel(on, max_rows)

    def ginv(self) -> PseudoInverse:
        return self.of.ginv().T


def _forward(name):
    def op(self, x):
        return Transposed(getattr(self.of, name)(x))

    return op


for _n in ("__add__", "__radd__", "__sub__", "__rsub__", "__mul__", "__rmul__", "__truediv__", "__rtruediv__", "__pow__", "__rpow__", "__mod__", "__gt__"):
    setattr(Transposed, _n, _forward(_n))


class PseudoInverse:
    """pinv(T) held as factors: P (d x d) and T itself."""

    def __init__(self, of: Matrix, p: np.ndarray, flipped: bool = False):
        self.of, self.p, self.flipped = of, p, flipped

    @property
    def T(self):  # noqa: N802
        return PseudoInverse(self.of, self.p, not self.flipped)

    def __matmul__(self, b):
        """pinv(T) b for n-row b (one fold), or pinv(T^T) x = T P x for d-row x (one scoring)."""
        return self.of @ (self.p @ b) if self.flipped else self.p @ self.of.folded(b)

    def rows(self) -> RowMatrix:
        """The n x d transpose of pinv(T), beside T's rows."""
        return self.of.scored(self.p)


class RowPseudoInverse:
    """pinv(T) = T^T pinv(T T^T) of a matrix with no more rows than columns, from its parts on the driver."""

    def __init__(self, of: Matrix):
        from foldstar.double import short

        self.of, x = of, short(of)
        self.dense = x.T @ dense.pinv(x @ x.T)

    def __matmul__(self, b) -> np.ndarray:
        """pinv(T) b for n x m values beside the rows, or an array in the order of `_row`."""
        if isinstance(b, RowMatrix):
            b = b.frame.orderBy("_row").select(*b.cols).toPandas().to_numpy(dtype=float)  # n <= SHORT_ROWS
        return self.dense @ b

    @property
    def T(self) -> np.ndarray:  # noqa: N802
        return self.dense.T


def _columns(x, d: int) -> np.ndarray:
    x = np.asarray(x, dtype=float)
    x = x.reshape(-1, 1) if x.ndim == 1 else x
    if x.shape[0] != d:
        raise ValueError(f"{x.shape[0]} rows do not meet {d} columns")
    return x
