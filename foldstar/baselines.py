"""What the factored engine is compared with."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from foldstar import dense

#: The hash probe keeps a block's partial products in every worker, so its size is bounded and checked.
HASH_ROWS = 2_000_000


def hash_glm(entity: DataFrame, own: list[str], fk: str, block: DataFrame, key: str, names: list[str], y: str, alpha: float, iters: int, max_rows: int = HASH_ROWS) -> np.ndarray:
    """Logistic regression specific to one key join: partial inner products of the block in an associative array.

    Each round sends {key: partial product} to the workers, where entity rows probe it. Blocks beyond
    max_rows are refused: use the factored matrix, which shuffles instead.
    """
    if block.count() > max_rows:
        raise ValueError(f"more than {max_rows} targets; the hash probe keeps them in every worker")
    spark = entity.sparkSession
    b = block.select(key, *[dense.d(c).alias(c) for c in names]).toPandas()
    keys, x = b[key].to_numpy(), b[names].to_numpy(dtype=float)
    slim = entity.select(F.col(fk).alias("_fk"), F.col(y).cast("double").alias("_y"), *[dense.d(c).alias(c) for c in own])
    w = np.zeros(len(own) + len(names))
    for _ in range(iters):
        partial = spark.sparkContext.broadcast(dict(zip(keys.tolist(), (x @ w[len(own) :]).tolist())))
        mine = w[: len(own)]

        def step(frames, partial=partial, mine=mine):
            held, total = {}, np.zeros(len(own))
            for f in frames:
                e = f[own].to_numpy(dtype=float)
                yy = f["_y"].to_numpy()
                s = e @ mine + f["_fk"].map(partial.value).to_numpy(dtype=float)
                p = yy / (1 + np.exp(yy * s))
                total += e.T @ p
                for k, v in pd.Series(p).groupby(f["_fk"].to_numpy()).sum().items():
                    held[k] = held.get(k, 0.0) + v
            yield pd.DataFrame({"k": [-1 - i for i in range(len(own))] + list(held), "own": [True] * len(own) + [False] * len(held), "v": [*total, *held.values()]})

        got = slim.mapInPandas(step, "k long, own boolean, v double").groupBy("k", "own").agg(F.sum("v").alias("v")).toPandas()
        mine_g = got[got["own"]].set_index("k")["v"]
        theirs = got[~got["own"]].set_index("k")["v"].reindex(keys, fill_value=0.0).to_numpy()
        grad = np.concatenate([[mine_g.get(-1 - i, 0.0) for i in range(len(own))], x.T @ theirs])
        partial.unpersist()
        w = w + alpha * grad
    return w


def chunked_gram(frame: DataFrame, names: list[str]) -> np.ndarray:
    """Row-chunk execution on a joined table: one product per batch, summed."""
    return dense.products(frame, names, lane="arrow")


def ml_linear(frame: DataFrame, names: list[str], y: str) -> np.ndarray:
    """Spark ML on the joined table, as an outside yardstick."""
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import LinearRegression

    made = VectorAssembler(inputCols=names, outputCol="_x").transform(frame).select("_x", F.col(y).cast("double").alias("_y"))
    m = LinearRegression(featuresCol="_x", labelCol="_y", fitIntercept=False, solver="normal").fit(made)
    return m.coefficients.toArray()
