"""Links that are derived rather than given: by range, as of a time, or checked for integrity."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def range_link(df: DataFrame, value: str, bands: DataFrame, low: str, high: str, key: str, width: float) -> DataFrame:
    """Adds `key` of the band with low <= value < high.

    Bands are laid out over bins of `width`, so the join is an equi-join on the bin and the range test
    is a filter within it: no nested loop over all pairs.
    """
    lo, hi = F.floor(F.col(low) / width), F.floor(F.col(high) / width)
    laid = bands.select(key, low, high, F.explode(F.sequence(lo.cast("long"), hi.cast("long"))).alias("_bin"))
    binned = df.withColumn("_bin", F.floor(F.col(value) / width).cast("long"))
    return binned.join(laid, "_bin").where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("_bin", low, high)


def asof_link(events: DataFrame, on: str, at: str, states: DataFrame, state_on: str, since: str, key: str) -> DataFrame:
    """Adds `key` of the latest state of the same entity that is not later than the event (null: none).

    One union sorted by time within the entity, and the last key seen: no join of all pairs in time.
    Ties in time go to the largest key.
    """
    cols = events.columns
    left = events.select(F.col(on).alias("_e"), F.col(at).alias("_t"), F.lit(1).alias("_kind"), F.lit(None).cast(states.schema[key].dataType).alias("_key"), F.struct(*cols).alias("_row"))
    right = states.select(F.col(state_on).alias("_e"), F.col(since).alias("_t"), F.lit(0).alias("_kind"), F.col(key).alias("_key"), F.lit(None).cast(left.schema["_row"].dataType).alias("_row"))
    w = Window.partitionBy("_e").orderBy("_t", "_kind", "_key").rowsBetween(Window.unboundedPreceding, 0)
    seen = left.unionByName(right).withColumn("_last", F.last("_key", ignorenulls=True).over(w))
    return seen.where("_kind = 1").select("_row.*", F.col("_last").alias(key))


def dangling(df: DataFrame, fk: str, target: DataFrame, key: str) -> DataFrame:
    return df.join(target, df[fk] == target[key], "left_anti")


def referenced(target: DataFrame, key: str, df: DataFrame, fk: str) -> DataFrame:
    return target.join(df, target[key] == df[fk], "left_semi")


def fold_all(df: DataFrame, keys: list[str], sums: list[str], mode: str = "gsets") -> DataFrame:
    """Folds along several links at once: grouping sets, cube or rollup; `level` tells which link a row is of."""
    if mode == "gsets":
        g = df.groupingSets([[k] for k in keys], *keys)
    else:
        g = getattr(df, mode)(*keys)
    return g.agg(F.grouping_id().alias("level"), F.count("*").alias("hits"), *[F.sum(c).alias(c) for c in sums])
