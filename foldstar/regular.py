"""The baseline representation: one joined table."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from foldstar import dense
from foldstar.matrix import Matrix, RowMatrix


class RegularMatrix(Matrix):
    def __init__(self, frame: DataFrame, names: list[str]):
        self.frame, self.names = frame, list(names)

    def row_frame(self) -> DataFrame:
        return self.frame

    def on(self, rows: DataFrame) -> RegularMatrix:
        return RegularMatrix(rows, self.names)

    def n_rows(self) -> int:
        return self.frame.count()

    def cache(self) -> RegularMatrix:
        self.frame.persist().count()
        return self

    def row_matrix(self, *columns: str) -> RowMatrix:
        names = [f"_v{i}" for i in range(len(columns))]
        return RowMatrix(self.frame.select("*", *[dense.d(c).alias(n) for c, n in zip(columns, names)]), names, self)

    def mapped(self, f, keeps_zero: bool) -> RegularMatrix:
        return RegularMatrix(self.frame.withColumns({c: f(F.col(f"`{c}`")).cast("double") for c in self.names}), self.names)

    def row_sums(self) -> RowMatrix:
        return self.scored(np.ones((self.d, 1)))

    def with_row_sums(self, name: str, f) -> RegularMatrix:
        total = F.lit(0.0)
        for c in self.names:
            total = total + f(F.col(f"`{c}`"))
        return self.on(self.frame.withColumn(name, total))

    def col_sums(self) -> np.ndarray:
        return dense.sums(self.frame, self.names)

    def sum(self) -> float:
        return float(self.col_sums().sum())

    def scored(self, x: np.ndarray) -> RowMatrix:
        from foldstar.normalized import _dot

        cols = [f"_v{j}" for j in range(x.shape[1])]
        keep = [F.col(f"`{c}`") for c in self.frame.columns if not c.startswith("_v")]
        return RowMatrix(self.frame.select(*keep, *[_dot(self.names, x[:, j]).alias(c) for j, c in enumerate(cols)]), cols, self)

    def folded(self, r: RowMatrix, extra: list = ()) -> np.ndarray | tuple[np.ndarray, np.ndarray]:
        """T^T R; with `extra` (columns over R's frame) also their sums, in the same pass."""
        d, m = self.d, len(r.cols)
        if d * m + len(extra) <= dense.SQL_PRODUCTS:
            got = dense.sums(r.frame, [dense.d(c) * F.col(v) for c in self.names for v in r.cols] + list(extra))
        else:
            def partial(x):
                return np.concatenate([(x[:, :d].T @ x[:, d : d + m]).ravel(), x[:, d + m :].sum(axis=0)])

            got = dense.gathered([(dense.flat(r.frame, [*self.names, *r.cols, *extra], partial, d * m + len(extra)), d * m + len(extra))])[0]
        out = got[: d * m].reshape(d, m)
        return (out, got[d * m :]) if len(extra) else out

    def gram(self, **_) -> np.ndarray:
        return dense.products(self.frame, self.names)

    def collect(self) -> np.ndarray:
        return self.frame.select(*[dense.d(c) for c in self.names]).toPandas().to_numpy(dtype=float)
