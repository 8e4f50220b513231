"""Co-factors kept up to date by streams: counts, sums and products add up over entity rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    """Files of a folder as a stream; event times are UTC timestamps."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger).parquet(path)


def cofactors(events: DataFrame, customers: DataFrame, window: tuple[str, str | None], watermark: str | None = None) -> DataFrame:
    """Per time window: n, sums and products of event value (v) and customer balance (b).

    Works on a batch or a stream. Events are folded to (window, customer) before they meet the
    customer table, so its features are read once per key.
    """
    v = F.round("value")
    c = customers.select("c_custkey", F.round("c_acctbal").alias("b"))
    size, slide = window
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    if events.isStreaming:
        e = events.withWatermark("ts", watermark) if watermark else events
        joined = e.join(c, e["user_id"] == c["c_custkey"])
        out = joined.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.sum(v).alias("v"), F.sum("b").alias("b"), F.sum(v * v).alias("vv"), F.sum(v * F.col("b")).alias("vb"), F.sum(F.col("b") * F.col("b")).alias("bb"))
    else:
        folded = events.groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n"), F.sum(v).alias("v"), F.sum(v * v).alias("vv"))
        b = F.col("b")
        out = folded.join(c, F.col("user_id") == F.col("c_custkey")).groupBy("w").agg(F.sum("n").alias("n"), F.sum("v").alias("v"), F.sum(F.col("n") * b).alias("b"), F.sum("vv").alias("vv"), F.sum(F.col("v") * b).alias("vb"), F.sum(F.col("n") * b * b).alias("bb"))
    return out.select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("start"), "n", "v", "b", "vv", "vb", "bb")


class RunningGram:
    """foreachBatch sink: adds each batch's Gram matrix to a running one (d x d on the driver).

    Batches that were added before are told by their number, so a repeated batch counts once.
    """

    def __init__(self, build):
        self.build, self.total, self.n, self.seen = build, None, 0, set()

    def __call__(self, batch: DataFrame, number: int) -> None:
        if number in self.seen:
            return
        t = self.build(batch)
        g = t.gram()
        self.total = g if self.total is None else self.total + g
        self.n += t.n_rows()
        self.seen.add(number)


def distinct_events(events: DataFrame, watermark: str = "2 hours") -> DataFrame:
    """Late copies of an event within the watermark are dropped."""
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def interval_join(left: DataFrame, right: DataFrame, within: str = "10 minutes", watermark: str = "1 hour") -> DataFrame:
    """Pairs of one user's events of two streams, the right one at most `within` later."""
    a = left.withWatermark("ts", watermark).select(F.col("user_id").alias("u1"), F.col("ts").alias("t1"), F.col("event_id").alias("id1"))
    b = right.withWatermark("ts", watermark).select(F.col("user_id").alias("u2"), F.col("ts").alias("t2"), F.col("event_id").alias("id2"))
    return a.join(b, F.expr(f"u1 = u2 AND t2 >= t1 AND t2 <= t1 + INTERVAL {within}"))
