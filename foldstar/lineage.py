"""Frames written and read again, so that lineage ends: iterative methods call this once a round."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_SWEEP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def swept(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of a write made inside go when it ends, not when the driver next happens to collect garbage."""
    before = spark.conf.get(_SWEEP, None)
    spark.conf.set(_SWEEP, "true")
    try:
        yield
    finally:
        spark.conf.unset(_SWEEP) if before is None else spark.conf.set(_SWEEP, before)


def cut(frame: DataFrame, tag: str = "round") -> DataFrame:
    """`frame` as a Parquet table below spark.checkpoint.dir; without that setting a temporary folder, on one machine only."""
    spark = frame.sparkSession
    sc = spark.sparkContext
    root = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
    if not root:
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to storage that driver and executors share")
        root = getattr(sc, "_foldstar_rounds", None) or tempfile.mkdtemp(prefix="foldstar-rounds-")
        sc._foldstar_rounds = root
    path = f"{root.rstrip('/')}/foldstar/{tag}-{uuid.uuid4().hex}"
    with swept(spark):
        frame.write.parquet(path)
    out = spark.read.schema(frame.schema).parquet(path)
    out._cut_at = path
    return out


def dropped(*frames: DataFrame) -> None:
    """Delete tables that `cut` returned: nothing may read them any more. Other frames are left alone."""
    for frame in frames:
        if (path := getattr(frame, "_cut_at", None)) is not None:
            sc = frame.sparkSession.sparkContext
            at = sc._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(sc._jsc.hadoopConfiguration()).delete(at, True)
