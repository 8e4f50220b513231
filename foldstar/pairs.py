"""Join indexes kept as their tables: the pairs of a chain of equi-joins are made last, or not at all."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from foldstar.lineage import cut, dropped

#: Rows of a side that meet another side's at once: a block of pairs is an array of this squared.
BLOCK = 1000
#: Groups of pairs dealt out for each shuffle partition where a join makes many more rows than it reads.
SPREAD = 4


@dataclass
class ChainIndex:
    """tables[i] has _p{i} (its key), _l{i} (meets _r{i - 1}; not the first) and _r{i} (not the last).

    labels: row columns made of the keys, name to a function of them that is right for Columns and arrays.
    """

    tables: list[DataFrame]
    labels: dict[str, Callable] = field(default_factory=dict)

    def _named(self, frame: DataFrame) -> DataFrame:
        keys = [F.col(f"_p{i}") for i in range(len(self.tables))]
        return frame.withColumns({n: f(*keys) for n, f in self.labels.items()})

    def rows(self) -> DataFrame:
        """The pairs, table by table."""
        out = self.tables[0]
        for i, part in enumerate(self.tables[1:], 1):
            out = out.join(part, F.col(f"_r{i - 1}") == F.col(f"_l{i}")).drop(f"_r{i - 1}", f"_l{i}")
        return self._named(out)

    def beside(self, values: list[DataFrame | None]) -> DataFrame:
        """The pairs with columns of their tables' keys: values[i] has _key and what goes along with table i (None: nothing).

        Neighbours with the fewest pairs are joined first, and the join that makes the most rows comes last:
        its result crosses no shuffle. What comes before is written and its shuffle files go, so that only the
        sides of the last join and their shuffle are on disk beside the result.
        """
        parts = [(t if v is None else cut(t.join(v, t[f"_p{i}"] == v["_key"]).drop("_key"), "pair-side"), i, i) for i, (t, v) in enumerate(zip(self.tables, values))]
        while len(parts) > 1:
            met = [_met(a[0], b[0], f"_r{a[2]}", f"_l{b[1]}") for a, b in zip(parts, parts[1:])]
            k = min(range(len(met)), key=lambda i: met[i][0])
            a, b = parts[k], parts[k + 1]
            both = _joined(a[0], b[0], f"_r{a[2]}", f"_l{b[1]}", *met[k])
            if len(parts) > 2:
                both = cut(both, "pair-side")
                dropped(a[0], b[0])
            parts[k : k + 2] = [(both, a[1], b[2])]
        return self._named(parts[0][0])

    def folds(self, scores: list[DataFrame], y: str, residual: Callable) -> list[DataFrame]:
        """Sums of residual(score, label) over the pairs of each key, for two tables: _p{i} and v.

        scores[i] has _key and s, which add up to a pair's score. Pairs meet in blocks of arrays that are never stored.
        """
        label, packed = self.labels[y], []
        for i, (t, s, side) in enumerate(zip(self.tables, scores, ("_r0", "_l1"))):
            one = t.join(s, t[f"_p{i}"] == s["_key"]).select(F.col(side).alias("j"), F.col(f"_p{i}").alias("k"), "s").where("j is not null")
            many = one.groupBy("j").agg(F.ceil(F.count("*") / BLOCK).alias("parts"))
            dealt = one.join(many, "j").groupBy("j", F.pmod(F.xxhash64("k"), F.col("parts")).alias("part"))
            packed.append(dealt.agg(F.collect_list("k").alias(f"k{i}"), F.collect_list("s").alias(f"s{i}")).drop("part"))

        def run(frames):
            for f in frames:
                for a, u, b, v in zip(f["k0"], f["s0"], f["k1"], f["s1"]):
                    with np.errstate(over="ignore"):
                        r = residual(u[:, None] + v, label(a[:, None], b), np.exp)
                    yield pd.DataFrame({"side": np.repeat([0, 1], [len(a), len(b)]), "k": np.concatenate([a, b]), "v": np.concatenate([r.sum(axis=1), r.sum(axis=0)])})

        n = int(packed[0].sparkSession.conf.get("spark.sql.shuffle.partitions"))
        met = packed[0].join(packed[1], "j").drop("j").repartition(n * SPREAD)
        sums = cut(met.mapInPandas(run, "side int, k long, v double").groupBy("side", "k").agg(F.sum("v").alias("v")), "pair-folds")
        return [sums.where(F.col("side") == i).select(F.col("k").alias(f"_p{i}"), "v") for i in (0, 1)]


def _met(a: DataFrame, b: DataFrame, on_a: str, on_b: str) -> tuple:
    """Pairs of a join, those of its most frequent key, rows of a and of b that have a partner."""
    x = a.groupBy(F.col(on_a).alias("j")).agg(F.count("*").alias("x"))
    y = b.groupBy(F.col(on_b).alias("j")).agg(F.count("*").alias("y"))
    n = F.col("x") * F.col("y")
    sums = [F.coalesce(f, F.lit(0)).alias(c) for f, c in ((F.sum(n), "pairs"), (F.max(n), "most"), (F.sum("x"), "rows_a"), (F.sum("y"), "rows_b"))]
    r = cut(x.join(y, "j").agg(*sums), "pair-counts")  # a write, so that its shuffle files go
    out = tuple(r.first())
    dropped(r)
    return out


def _joined(a: DataFrame, b: DataFrame, on_a: str, on_b: str, pairs: int, most: int, rows_a: int, rows_b: int) -> DataFrame:
    """The join, its columns on_a and on_b dropped. Where it makes many rows, a key's rows are dealt to several tasks: the shorter side goes to all of them."""
    if rows_a < rows_b:
        a, b, on_a, on_b = b, a, on_b, on_a
    if pairs > 8 * (rows_a + rows_b):
        n = int(a.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        salts = max(1, -(-SPREAD * n * most // pairs))
        a = a.withColumn("_salt", F.pmod(F.xxhash64(*[c for c in a.columns if c.startswith("_p")]), F.lit(salts)).cast("int"))
        b = b.withColumn("_salt2", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
        # a merge join at every size: with a broadcast the files of one side would be all the tasks there are
        return a.join(b.hint("merge"), (F.col(on_a) == F.col(on_b)) & (F.col("_salt") == F.col("_salt2"))).drop(on_a, on_b, "_salt", "_salt2")
    return a.join(b, F.col(on_a) == F.col(on_b)).drop(on_a, on_b)
