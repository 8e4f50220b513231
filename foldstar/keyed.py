"""Many-to-many joins without pairs: sums per join value, for everything linear in the rows."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from foldstar import dense


class KeyedJoin:
    """Chain of equi-joins of wide tables; two tables are the plain M:N join, no condition a Cartesian one.

    tables: (frame, features). conditions[i] = (column of table i, column of table i + 1). Each row's
    multiplicity in T follows from counts passed along the chain, one group-by and one join a step;
    work is linear in the inputs, however many pairs there are.
    """

    def __init__(self, tables: list[tuple[DataFrame, list[str]]], conditions: list[tuple[str, str]] | None):
        self.names_of = [list(n) for _, n in tables]
        self.frames = []
        for i, (df, names) in enumerate(tables):
            links = []
            if conditions is None:
                links = [F.lit(0).alias("_up"), F.lit(0).alias("_down")]
            else:
                links.append((F.col(f"`{conditions[i - 1][1]}`") if i else F.lit(0)).alias("_up"))
                links.append((F.col(f"`{conditions[i][0]}`") if i < len(conditions) else F.lit(0)).alias("_down"))
            keys = [F.col(c) for c in df.columns if c == f"_p{i}"]
            self.frames.append(df.select(*links, *keys, *[dense.d(c).alias(c) for c in names]))
        self.q = len(tables)

    @property
    def names(self) -> list[str]:
        return [n for names in self.names_of for n in names]

    def _counts(self, upto: int, left: bool) -> DataFrame | None:
        """Columns _v, _n: join value at table `upto`'s border and how many partial rows beyond meet it."""
        if left:
            n = None
            for i in range(upto):
                f = self.frames[i]
                f = f.withColumn("_n", F.lit(1)) if n is None else f.join(n, f["_up"] == n["_v"]).drop("_v")
                n = f.groupBy(F.col("_down").alias("_v")).agg(F.sum("_n").alias("_n"))
            return n
        n = None
        for i in range(self.q - 1, upto, -1):
            f = self.frames[i]
            f = f.withColumn("_n", F.lit(1)) if n is None else f.join(n, f["_down"] == n["_v"]).drop("_v")
            n = f.groupBy(F.col("_up").alias("_v")).agg(F.sum("_n").alias("_n"))
        return n

    def weighted(self, i: int) -> DataFrame:
        """Table i with `_w`: how often each of its rows is in T."""
        f = self.frames[i]
        left, right = self._counts(i, True), self._counts(i, False)
        a = b = F.lit(1)
        if left is not None:
            left = left.select(F.col("_v").alias("_lv"), F.col("_n").alias("_ln"))
            f, a = f.join(left, f["_up"] == left["_lv"]), F.col("_ln")
        if right is not None:
            right = right.select(F.col("_v").alias("_rv"), F.col("_n").alias("_rn"))
            f, b = f.join(right, f["_down"] == right["_rv"]), F.col("_rn")
        return f.withColumn("_w", (a * b).cast("double"))

    def n_rows(self) -> int:
        return int(dense.sums(self.weighted(0), ["_w"])[0])

    def expansion(self) -> float:
        """Rows of T over rows of the inputs."""
        return self.n_rows() / max(sum(f.count() for f in self.frames), 1)

    def col_sums(self) -> np.ndarray:
        return np.concatenate([dense.sums(self.weighted(i), [F.col("_w") * F.col(f"`{c}`") for c in names]) for i, names in enumerate(self.names_of)])

    def sum(self) -> float:
        return float(self.col_sums().sum())

    def gram(self, diagonal: bool = True) -> np.ndarray:
        off = np.concatenate([[0], np.cumsum([len(n) for n in self.names_of])])
        out = np.zeros((off[-1], off[-1]))
        for i, names in enumerate(self.names_of):
            if diagonal:
                out[off[i] : off[i + 1], off[i] : off[i + 1]] = dense.products(self.weighted(i), names, weight="_w")
            # carry sums of table i's features down the chain, one join value at a time
            f = self.frames[i]
            left = self._counts(i, True)
            if left is not None:
                f = f.join(left, f["_up"] == left["_v"]).drop("_v")
            else:
                f = f.withColumn("_n", F.lit(1))
            cols = [f"_u{k}" for k in range(len(names))]
            carried = f.groupBy(F.col("_down").alias("_v")).agg(*[F.sum(F.col("_n") * F.col(f"`{c}`")).alias(u) for c, u in zip(names, cols)])
            for j in range(i + 1, self.q):
                met = self.frames[j].join(carried, self.frames[j]["_up"] == carried["_v"]).drop("_v")
                right = self._counts(j, False)
                if right is not None:
                    w = met.join(right, met["_down"] == right["_v"]).drop("_v")
                    w = w.withColumns({u: F.col(u) * F.col("_n") for u in cols})
                else:
                    w = met
                cross = dense.products(w, cols, self.names_of[j])
                out[off[i] : off[i + 1], off[j] : off[j + 1]] = cross
                out[off[j] : off[j + 1], off[i] : off[i + 1]] = cross.T
                carried = met.groupBy(F.col("_down").alias("_v")).agg(*[F.sum(u).alias(u) for u in cols])
        return out

    def folded_linear(self, w: np.ndarray, y: str | None = None) -> np.ndarray:
        """T^T (T w - y) with y a feature of T by name: linear, so the Gram is enough."""
        g = self.gram()
        r = g @ np.asarray(w, dtype=float)
        return r - g[:, self.names.index(y)] if y else r
