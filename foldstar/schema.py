"""Feature specifications: which columns of a table become which numeric features."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from foldstar.lineage import cut
from foldstar.normalized import Coo, KeyNames, Wide


@dataclass
class FeatureSpec:
    """numeric: name -> column expression; onehot: column -> values (None: all that occur, sorted).

    key_onehot adds the key itself as identity columns (sparse); leave it out where the key's domain is
    open for the task. hashed: text columns whose words are counted in 2**bits buckets by MD5.
    """

    numeric: dict[str, Column] = field(default_factory=dict)
    onehot: dict[str, list | None] = field(default_factory=dict)
    hashed: list[str] = field(default_factory=list)
    key_onehot: bool = False
    bits: int = 12

    def _values(self, df: DataFrame) -> dict[str, list]:
        return {c: v if v is not None else [r[0] for r in df.select(c).where(F.col(c).isNotNull()).distinct().orderBy(c).collect()] for c, v in self.onehot.items()}

    def columns(self, df: DataFrame) -> dict[str, Column]:
        """Feature name to expression, for the wide layout."""
        out = {n: F.coalesce(c.cast("double"), F.lit(0.0)) for n, c in self.numeric.items()}
        for c, values in self._values(df).items():
            for i, v in enumerate(values):
                out[f"{c}_{i}"] = F.when(F.col(c) == v, 1.0).otherwise(0.0)
        return out

    def wide(self, df: DataFrame, key: str) -> Wide:
        cols = self.columns(df)
        return Wide(df.select(key, *[e.alias(n) for n, e in cols.items()]), key, list(cols))

    def coo(self, df: DataFrame, key: str) -> Coo:
        """Long form: numeric, one-hot, hashed, then identity columns of the key."""
        names, parts = [], []
        for n, c in self.numeric.items():
            parts.append(df.select(key, F.lit(len(names)).alias("col"), c.cast("double").alias("val")))
            names.append(n)
        for c, values in self._values(df).items():
            spark = df.sparkSession
            known = spark.createDataFrame([(v, len(names) + i) for i, v in enumerate(values)], f"`{c}` {df.schema[c].dataType.simpleString()}, col int")
            parts.append(df.select(key, c).join(known, c).select(key, "col", F.lit(1.0).alias("val")))
            names += [f"{c}_{i}" for i in range(len(values))]
        for c in self.hashed:
            words = df.select(key, F.explode(F.split(F.lower(c), r"\s+")).alias("w")).where("w <> ''")
            bucket = F.conv(F.substring(F.md5("w"), 1, 8), 16, 10).cast("long") % (1 << self.bits)
            parts.append(words.groupBy(key, (bucket + len(names)).cast("int").alias("col")).agg(F.count("*").cast("double").alias("val")))
            names += [f"{c}_{i}" for i in range(1 << self.bits)]
        if self.key_onehot:
            known = numbered(df.select(key), key, len(names))
            parts.append(known.select(key, "col", F.lit(1.0).alias("val")))
            names += KeyNames(key, known.count())
        long = parts[0]
        for p in parts[1:]:
            long = long.unionByName(p)
        return Coo(long.where("val <> 0"), key, names, df.select(key).distinct())


def numbered(keys: DataFrame, key: str, first: int = 0) -> DataFrame:
    """Distinct keys with `col`, their position in sorted order from `first` on: no key comes to the driver, only one count a range."""
    dealt = cut(keys.where(F.col(key).isNotNull()).distinct().repartitionByRange(key).withColumn("_p", F.spark_partition_id()), "keys")
    base, n = [], first
    for r in dealt.groupBy("_p").count().orderBy("_p").collect():
        base.append((r["_p"], n))
        n += r["count"]
    start = keys.sparkSession.createDataFrame(base, "_p int, _n long")
    at = F.row_number().over(Window.partitionBy("_p").orderBy(key)) - 1
    return cut(dealt.withColumn("_i", at).join(F.broadcast(start), "_p").select(key, (F.col("_n") + F.col("_i")).cast("int").alias("col")), "keys")


def packed(df: DataFrame, key: str, column: str, width: int, prefix: str = "x") -> Wide:
    """An array column as a wide block."""
    return Wide(df.select(key, *[F.get(F.col(column), F.lit(i)).cast("double").alias(f"{prefix}{i}") for i in range(width)]), key, [f"{prefix}{i}" for i in range(width)])


def binarize(c: Column, threshold: float, labels: str = "pm1") -> Column:
    return F.when(c > threshold, 1.0).otherwise(-1.0 if labels == "pm1" else 0.0)


def target_as_feature(t, y: str, name: str | None = None):
    """T with the row column `y` as its first own feature, for methods without a target (K-Means, factorizations)."""
    from foldstar.normalized import FactoredMatrix

    name = name or f"target_{y}"
    return FactoredMatrix(t.rows.withColumn(name, F.col(y).cast("double")), [name, *t.own], t.links, [*t.trace, "target as feature"])
