"""Connected components of a large edge table, and union-find for bounded groups."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from foldstar.llm.shared import ship, stored

MAX_ROUNDS = 60
#: An edge table of at most this many rows (16 MB) is finished by one task.
FEW = 1 << 20


def components(edges: DataFrame, few: int = FEW) -> DataFrame:
    """Columns a, b (long) to node, root: the smallest node that each node reaches.

    Large-star and small-star steps in turn, each a group-by of minima (combined map-side) and a
    join whose skewed side Spark can split; no neighbourhood is ever gathered. Every round is
    written to the shared folder. Rounds shrink the table; once it has at most `few` edges one task
    of that bounded size finishes it by union-find, with the same roots. Only a count and a checksum
    come to the driver. Nodes without edges do not appear; nulls and loops are dropped; an empty
    table gives an empty table.
    """
    e = edges.where("a is not null and b is not null and a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    e = stored(e, "edges")
    last = _mark(e)
    if last[0] == 0:
        return e.select(F.col("u").alias("node"), F.col("v").alias("root"))
    for _ in range(MAX_ROUNDS):
        if last[0] <= few:
            return _finished(e)
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v")))
        e = stored(small.distinct(), "edges")
        now = _mark(e)
        if now == last:
            break
        last = now
    else:
        raise RuntimeError(f"components did not settle in {MAX_ROUNDS} rounds")
    roots = e.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
    return e.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(roots)


def _finished(e: DataFrame) -> DataFrame:
    """Roots of all nodes of a small edge table u, v, in one task."""

    def run(frames):
        pairs = pd.concat(list(frames))
        nodes, at = np.unique(pairs[["u", "v"]].to_numpy().ravel(), return_inverse=True)
        forest = Forest(len(nodes))
        forest.add(at[0::2], at[1::2])
        yield pd.DataFrame({"node": nodes, "root": nodes[forest.up]})

    ship(e.sparkSession)
    kind = e.schema["u"].dataType.simpleString()
    return e.coalesce(1).mapInPandas(run, f"node {kind}, root {kind}")


def _mark(e: DataFrame) -> tuple:
    return tuple(e.agg(F.count("*"), F.coalesce(F.bit_xor(F.xxhash64("u", "v")), F.lit(0))).first())


class Forest:
    """Union-find over 0..n-1 with numpy batches of pairs; roots are the smallest members."""

    def __init__(self, n: int):
        self.up = np.arange(n)

    def add(self, a: np.ndarray, b: np.ndarray) -> None:
        up = self.up
        while len(a):
            a, b = up[a], up[b]
            differ = a != b
            a, b = a[differ], b[differ]
            if not len(a):
                break
            hi, lo = np.maximum(a, b), np.minimum(a, b)
            np.minimum.at(up, hi, lo)
            while True:
                nxt = up[up]
                if (nxt == up).all():
                    break
                up[:] = nxt


def groups(frames, keys: list[str]):
    """Whole groups (pandas frames) of a partition sorted by `keys`, whatever the batch borders."""
    held = []
    for f in frames:
        if not len(f):
            continue
        k = f[keys].to_numpy()
        cut = np.flatnonzero((k[1:] != k[:-1]).any(axis=1)) + 1
        bounds = [0, *cut.tolist(), len(f)]
        for s, t in zip(bounds, bounds[1:]):
            part = f.iloc[s:t]
            if held and s == 0 and (held[-1][keys].iloc[-1].to_numpy() != k[0]).any():
                yield held[0] if len(held) == 1 else pd.concat(held)
                held = []
            if s > 0 and held:
                yield held[0] if len(held) == 1 else pd.concat(held)
                held = []
            held.append(part)
    if held:
        yield held[0] if len(held) == 1 else pd.concat(held)
