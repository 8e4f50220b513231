"""Products with a factored matrix on both sides."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from foldstar.matrix import SHORT_ROWS, Matrix, RowMatrix, Transposed

#: Cells of a short factor on the driver (80 MB).
MAX_CELLS = 10_000_000

def short(t: Matrix, max_rows: int = SHORT_ROWS) -> np.ndarray:
    """A short matrix as an array in the order of `_row`: its rows are another matrix's columns, so they are few.

    A factored one is never joined: its rows come with link values, the targets they refer to come once,
    and the parts are put side by side here.
    """
    n = t.n_rows()
    if n > max_rows or n * t.d > MAX_CELLS:
        raise ValueError(f"{n} x {t.d} cells where columns of the left factor are expected; limits {max_rows} rows, {MAX_CELLS} cells")
    frame = t.row_frame()
    if "_row" not in frame.columns:
        raise ValueError("this needs a column `_row` that numbers the rows from 0")
    if not hasattr(t, "links"):
        return frame.orderBy("_row").select(*[F.col(f"`{c}`").cast("double") for c in t.names]).toPandas().to_numpy(dtype=float)
    got = frame.orderBy("_row").select(*[F.col(f"`{c}`") for c in dict.fromkeys([*t.own, *[k.column for k in t.links]])]).toPandas()
    parts = [got[t.own].to_numpy(dtype=float).reshape(n, -1)]
    for k in t.links:
        block = k.block.wide() if hasattr(k.block, "keys") else k.block
        used = block.df.join(frame.select(F.col(f"`{k.column}`").alias(block.key)).distinct(), block.key, "left_semi").toPandas()
        at = {v: i for i, v in enumerate(used[block.key])}
        parts.append(used[block.names].to_numpy(dtype=float)[[at[v] for v in got[k.column]]])
    return np.concatenate(parts, axis=1)


def product(a, b):
    """a @ b, dispatched on transposes.

    A B: the right factor is short (its rows are A's columns), so its parts are collected and A scores them.
    A^T B over the same rows: blocks of folds, see `cross`. A B^T: rows by rows, see `outer`.
    A^T B^T: the transpose of B A, a flag over values beside B's rows.
    """
    if isinstance(a, Transposed) and isinstance(b, Transposed):
        return product(b.T, a.T).T
    if isinstance(a, Transposed):
        return cross(a.of, b)
    if isinstance(b, Transposed):
        return outer(a, b.of)
    return a.scored(short(b))


def cross(a, b, method: str = "hybrid") -> np.ndarray:
    """A^T B for factored matrices over one row frame (b's rows must be a's).

    The stacked matrix [A, B] over the same rows is factored too; A^T B is a block of its Gram, and
    only that block is worked out. method "cooc" counts pairs of targets before features move.
    """
    from foldstar import dense
    from foldstar.normalized import FactoredMatrix, Link

    links = [*[Link(k.column, k.block) for k in a.links], *[Link(k.column, k.block) for k in b.links]]
    both = FactoredMatrix(a.rows, [*a.own, *[c for c in b.own if c not in a.own]], links)
    out = np.zeros((a.d, b.d))
    oa, ob = a.offsets(), b.offsets()
    if a.own and b.own:
        out[: oa[0], : ob[0]] = dense.products(both.rows, a.own, b.own)
    for i, k in enumerate(a.links):
        s = slice(oa[i], oa[i + 1])
        if b.own:
            f = both.rows.groupBy(k.column).agg(*[F.sum(F.col(f"`{c}`")).alias(c) for c in b.own])
            out[s, : ob[0]] = k.block.fold_product(f, k.column, b.own)
        for j, q in enumerate(b.links):
            out[s, ob[j] : ob[j + 1]] = both._cross(i, len(a.links) + j, method)
    for j, q in enumerate(b.links):
        if a.own:
            f = both.rows.groupBy(q.column).agg(*[F.sum(F.col(f"`{c}`")).alias(c) for c in a.own])
            out[: oa[0], ob[j] : ob[j + 1]] = q.block.fold_product(f, q.column, a.own).T
    return out


def outer(a, b, max_rows: int = 5000) -> DataFrame:
    """A B^T in long form (r, s, value) for matrices of equal width with numbered rows (`_row`): rows by rows.

    B is short and goes along as an array. Each target of A meets B's rows once, whatever the number of rows
    that refer to it; a row of A then adds the lists of its targets. Columns are one list on either side, so
    entity features of one side may meet block features of the other.
    """
    nb = b.n_rows()
    if a.d != b.d or nb > max_rows:
        raise ValueError(f"{a.d} columns by {nb} x {b.d}: widths must agree and the right factor stays within {max_rows} rows")
    x = short(b, max_rows).T
    off = [len(a.own), *a.offsets()[1:]] if hasattr(a, "links") else [a.d]

    def met(frame, names, part, out):
        """One array of len(part[0]) values for each row: its `names` times `part`."""

        @F.pandas_udf("array<double>")
        def times(values: pd.DataFrame) -> pd.Series:
            return pd.Series(list(values.to_numpy(dtype=float) @ part), dtype=object)

        return frame.withColumn(out, times(F.struct(*[F.col(f"`{c}`").cast("double").alias(f"c{i}") for i, c in enumerate(names)])))

    frame, lists = a.row_frame(), []
    own = a.own if hasattr(a, "links") else a.names
    if own:
        frame, lists = met(frame, own, x[: len(own)], "_l"), ["_l"]
    for i, k in enumerate(a.links if hasattr(a, "links") else []):
        block = k.block.wide() if hasattr(k.block, "keys") else k.block
        made = met(block.df, block.names, x[off[i] : off[i + 1]], f"_l{i}").select(F.col(f"`{block.key}`").alias(f"_k{i}"), f"_l{i}")
        frame = frame.join(made, F.col(f"`{k.column}`") == F.col(f"_k{i}"))
        lists.append(f"_l{i}")
    total = F.col(lists[0])
    for c in lists[1:]:
        total = F.zip_with(total, F.col(c), lambda u, v: u + v)
    return frame.select(F.col("_row").alias("r"), F.posexplode(total).alias("s", "value"))


def crossprod(a, b=None):
    """a^T b with either side factored or n x m values; one argument gives the Gram."""
    if b is None:
        return a.gram()
    if isinstance(a, RowMatrix):
        return b.folded(a).T
    if isinstance(b, RowMatrix):
        return a.folded(b)
    return cross(a, b)
