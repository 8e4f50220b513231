"""Scans and sinks around the engine."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def scan(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None, where=None) -> DataFrame:
    """Parquet with pruned columns and pushed filters."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.where(where) if where is not None else df
    return df.select(*columns) if columns else df


def scan_csv(spark: SparkSession, path: str, schema: str, header: bool = True) -> DataFrame:
    """CSV with a declared schema; a malformed row fails the read."""
    return spark.read.csv(path, schema=schema, header=header, mode="FAILFAST")


def scan_json(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.json(path, schema=schema)


def scan_orc(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.orc(path)


def scan_text(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.text(path)


def scan_jdbc(spark: SparkSession, url: str, table: str, column: str, low: int, high: int, parts: int, **options) -> DataFrame:
    """A table of a relational database in ranges of one column."""
    return spark.read.jdbc(url, table, column=column, lowerBound=low, upperBound=high, numPartitions=parts, properties=options)


def from_array(spark: SparkSession, x: np.ndarray, prefix: str = "x") -> DataFrame:
    """Rows of an array with their number in `id`."""
    x = np.asarray(x, dtype=float)
    return spark.createDataFrame([(i, *map(float, r)) for i, r in enumerate(x)], "id long, " + ", ".join(f"{prefix}{j} double" for j in range(x.shape[1])))


def to_array(df: DataFrame, names: list[str], order: str) -> np.ndarray:
    return df.orderBy(order).select(*names).toPandas().to_numpy(dtype=float)


def write(df: DataFrame, path: str, kind: str = "parquet", by: list[str] = (), mode: str = "errorifexists") -> None:
    """kind: parquet, csv, json, orc or noop; `by` are partition columns."""
    if kind == "noop":
        df.write.format("noop").mode("overwrite").save()
        return
    w = df.write.mode(mode)
    w = w.partitionBy(*by) if by else w
    (w.option("header", True) if kind == "csv" else w).format(kind).save(path)


def write_bucketed(df: DataFrame, table: str, column: str, buckets: int) -> None:
    """Co-located by key, so that later looks and folds on it need no exchange."""
    df.write.bucketBy(buckets, column).sortBy(column).mode("overwrite").saveAsTable(table)


def save_model(path: str, names: list[str], **arrays) -> None:
    with open(path, "w") as f:
        json.dump({"names": names, **{k: np.asarray(v).tolist() for k, v in arrays.items()}}, f)


def load_model(path: str) -> dict:
    with open(path) as f:
        d = json.load(f)
    return {k: v if k == "names" else np.array(v) for k, v in d.items()}


def hash_split(df: DataFrame, key: str, parts: int, part: int) -> DataFrame:
    """A deterministic share of the rows."""
    return df.where(F.pmod(F.col(key) * 2654435761, F.lit(parts)) == part)
