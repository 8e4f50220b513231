"""Seeded synthetic tables of given dimensions, the same whatever the partitions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from foldstar.normalized import FactoredMatrix, Wide


def _cell(seed: int, j: int, whole: int | None) -> Column:
    h = F.pmod(F.xxhash64(F.col("id"), F.lit(seed * 10_007 + j)), F.lit(1_000_003))
    return (h % whole).cast("double") if whole else h / 1_000_003.0


def block(spark: SparkSession, n: int, d: int, seed: int, prefix: str, whole: int | None = 10) -> DataFrame:
    return spark.range(n).select("id", *[_cell(seed, j, whole).alias(f"{prefix}{j}") for j in range(d)])


def key_join(spark: SparkSession, n_e: int, d_e: int, blocks: list[tuple[int, int]], seed: int = 1, whole: int | None = 10) -> FactoredMatrix:
    """Entity of n_e rows; every target of a block is referred to while n_e reaches its size. `y` is -1 or 1."""
    e = block(spark, n_e, d_e, seed, "e", whole)
    for i, (n, _) in enumerate(blocks):
        e = e.withColumn(f"k{i}", F.pmod(F.col("id") * (2 * i + 1) + F.lit(i), F.lit(n)))
    e = e.withColumn("y", F.when(F.pmod(F.xxhash64("id", F.lit(seed + 77)), F.lit(2)) == 0, 1.0).otherwise(-1.0))
    parts = [(block(spark, n, d, seed + 1 + i, f"a{i}_", whole), f"k{i}", "id", [f"a{i}_{j}" for j in range(d)]) for i, (n, d) in enumerate(blocks)]
    return FactoredMatrix.star(e, parts, [f"e{j}" for j in range(d_e)], ["id", "y"], total=True)


def many_to_many(spark: SparkSession, n: int, d: int, n_u: int, seed: int = 1, whole: int | None = 10) -> tuple[DataFrame, DataFrame]:
    """Two tables of n rows and d features (a*, b*) with a join column j of n_u values."""
    made = []
    for s, p in ((seed, "a"), (seed + 1, "b")):
        made.append(block(spark, n, d, s, p, whole).withColumn("j", F.pmod(F.xxhash64("id", F.lit(s)), F.lit(n_u))))
    return made[0], made[1]


def wide(df: DataFrame, prefix: str, d: int) -> Wide:
    return Wide(df, "id", [f"{prefix}{j}" for j in range(d)])
