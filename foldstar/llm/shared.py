"""What the operators of this subpackage have in common: tables, working folders, code shipping."""

from __future__ import annotations

import io
import os
import tempfile
import uuid
import zipfile
from collections.abc import Callable
from contextvars import ContextVar
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from foldstar.lineage import swept


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir of the session.

    Where the setting is absent a temporary folder is made, but only on one machine; a cluster needs the setting.
    """
    sc = spark.sparkContext
    path = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
    if not path:
        path = getattr(sc, "_foldstar_dir", None)
        if path is None:
            if not sc.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to storage that driver and executors share")
            path = sc._foldstar_dir = tempfile.mkdtemp(prefix="foldstar-")
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        sc.setCheckpointDir(path)
    return path


def work_path(spark: SparkSession, tag: str) -> str:
    """A fresh path below the shared folder."""
    return f"{shared_dir(spark).rstrip('/')}/foldstar/{tag}-{uuid.uuid4().hex}"


def stored(df: DataFrame, tag: str) -> DataFrame:
    """Write `df` as Parquet to the shared folder and read it again: lineage ends there, and its shuffle files go.

    A lost executor costs at most the tasks it ran; everything before is on shared storage.
    """
    spark = df.sparkSession
    path = work_path(spark, tag)
    with swept(spark):
        df.write.parquet(path)
    if (scope := _SCOPE.get()) is not None:
        scope.append(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._stored_at = path
    return out


#: Paths that `stored` has written for the result that `settled` is making.
_SCOPE: ContextVar[list[str] | None] = ContextVar("scope", default=None)


def _delete(spark: SparkSession, path: str) -> None:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def released(*frames: DataFrame) -> None:
    """Delete tables that `stored` returned: every result made of them must be written by now. Other frames are left alone."""
    for df in frames:
        if (path := getattr(df, "_stored_at", None)) is not None:
            _delete(df.sparkSession, path)


def settled(make: Callable[[], DataFrame], tag: str) -> DataFrame:
    """`stored(make(), tag)`, after which the tables that make() stored are deleted: only its result may read them.

    After an error they stay.
    """
    inside: list[str] = []
    token = _SCOPE.set(inside)
    try:
        out = stored(make(), tag)
    finally:
        _SCOPE.reset(token)
    for path in inside[:-1]:
        _delete(out.sparkSession, path)
    if (scope := _SCOPE.get()) is not None:
        scope.append(inside[-1])
    return out


#: Rows of an Arrow batch where the session has Spark's default: whole texts are long rows.
BATCH_ROWS = 1000


def ship(spark: SparkSession) -> None:
    """Make this package importable in Python workers, once a session; bound Arrow batches of texts."""
    sc = spark.sparkContext
    batch = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if spark.conf.get(batch) == "10000":
        spark.conf.set(batch, str(BATCH_ROWS))
    if getattr(sc, "_foldstar_shipped", False):
        return
    root = Path(__file__).resolve().parents[1]
    buffer = io.BytesIO()
    with zipfile.ZipFile(buffer, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, p.relative_to(root.parent))
    path = os.path.join(tempfile.mkdtemp(prefix="foldstar-code-"), "foldstar.zip")
    Path(path).write_bytes(buffer.getvalue())
    sc.addPyFile(path)
    sc._foldstar_shipped = True


def words(text) -> F.Column:
    """The words `[^\\x20\\x09-\\x0D]+` of a text column as an array (null: empty array)."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), "[ \\t-\\r]+", -1), "")


def filtered(df: DataFrame, condition) -> DataFrame:
    """`df.where(condition)` that is judged after the columns of `df` are made, once.

    A plain filter is pushed below the projections it reads and repeats their expressions there; a
    column that is not deterministic keeps it above.
    """
    at = "_at"
    while at in df.columns:
        at += "_"
    return df.withColumn(at, F.spark_partition_id()).where(condition & (F.col(at) >= 0)).drop(at)


def partitions(df: DataFrame, factor: int = 1) -> int:
    """A number of partitions that follows the session: its shuffle partitions times `factor`."""
    return max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")) * factor)
