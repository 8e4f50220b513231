"""Functions with Python in them: each has a built-in twin in the engine and exists for comparison or for users' blocks."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, StructType


@pandas_udf(DoubleType())
def sigmoid(x: pd.Series) -> pd.Series:
    """Arrow-batched activation; `Matrix.map("sigmoid")` is the built-in form."""
    return 1 / (1 + np.exp(-x))


@pandas_udf(ArrayType(DoubleType()))
def gram_of_packed(v: pd.Series) -> list:
    """Aggregate: flattened v^T v of an array column. Without partial aggregation, so only for bounded groups."""
    x = np.array([np.asarray(r, dtype=float) for r in v if r is not None])
    return (x.T @ x).ravel().tolist() if len(x) else []


@udtf(returnType=StructType().add("col", IntegerType()).add("val", DoubleType()))
class CooExplode:
    """Rows (position, value) of the non-zero cells of an array; null gives none."""

    def eval(self, values):
        for i, x in enumerate(values or ()):
            if x:
                yield i, float(x)


def kernel_tiles(df: DataFrame, key: str, names: list[str], tile: int = 512, max_rows: int = 20_000) -> DataFrame:
    """Row Gram (r, s, value), r <= s, by tiles: rows are dealt to pairs of tiles, one product per pair.

    Quadratic in rows, hence the limit; a task holds two tiles.
    """
    n = df.count()
    if n > max_rows:
        raise ValueError(f"{n} rows: the row Gram has their square; limit {max_rows}")
    tiles = max(1, -(-n // tile))
    rows = df.select(F.col(key).cast("long").alias("k"), F.pmod(F.xxhash64(key), F.lit(tiles)).alias("t"), F.array(*[F.col(c).cast("double") for c in names]).alias("x"))
    dealt = rows.withColumn("o", F.explode(F.sequence(F.lit(0), F.lit(tiles - 1)))).select(F.least("t", "o").alias("a"), F.greatest("t", "o").alias("b"), "t", "k", "x")

    def one(pair, f):
        a, b = f[f["t"] == pair[0]], f[f["t"] == pair[1]]
        if not len(a) or not len(b):
            return pd.DataFrame({"r": [], "s": [], "value": []})
        g = np.stack(a["x"].to_list()) @ np.stack(b["x"].to_list()).T
        r, s = np.meshgrid(a["k"], b["k"], indexing="ij")
        keep = r <= s if pair[0] == pair[1] else np.ones_like(r, dtype=bool)
        return pd.DataFrame({"r": np.minimum(r, s)[keep], "s": np.maximum(r, s)[keep], "value": g[keep]})

    return dealt.groupBy("a", "b").applyInPandas(one, "r long, s long, value double")
