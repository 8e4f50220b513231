import numpy as np
import pytest
from pyspark.sql import functions as F

from foldstar.normalized import FactoredMatrix
from foldstar.streaming import cofactor as C
from foldstar.workloads import read

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("events"))
    e = read(spark, SF, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    e.repartitionByRange(3, "ts").sortWithinPartitions("ts").write.mode("overwrite").parquet(path)
    return path


def drain(stream, name, mode):
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)


@pytest.mark.parametrize("window", [("1 day", None), ("1 day", "6 hours")])
def test_stream_equals_batch(spark, folder, window):
    customers = read(spark, SF, "customer")
    name = "cof" + ("s" if window[1] else "t")
    drain(C.cofactors(C.read_events(spark, folder), customers, window), name, "complete")
    want = C.cofactors(spark.read.schema(C.EVENTS).parquet(folder), customers, window)
    key = lambda r: r["start"]
    assert sorted(map(tuple, spark.table(name).collect())) == sorted(map(tuple, want.collect()))


def test_append_with_watermark(spark, folder):
    drain(C.cofactors(C.read_events(spark, folder), read(spark, SF, "customer"), ("1 day", None), "2 hours"), "cofa", "append")
    full = {r["start"]: tuple(r) for r in C.cofactors(spark.read.schema(C.EVENTS).parquet(folder), read(spark, SF, "customer"), ("1 day", None)).collect()}
    got = [tuple(r) for r in spark.table("cofa").collect()]
    assert got and all(full[r[0]] == r for r in got)


def test_running_gram_and_distinct(spark, folder):
    customers = read(spark, SF, "customer").select("c_custkey", F.round("c_acctbal").alias("b"))
    build = lambda df: FactoredMatrix.star(df.select("user_id", F.round("value").alias("v")), [(customers, "user_id", "c_custkey", ["b"])], ["v"], total=True)
    sink = C.RunningGram(build)
    twice = C.read_events(spark, folder).unionByName(C.read_events(spark, folder))
    q = C.distinct_events(twice).writeStream.foreachBatch(sink).trigger(availableNow=True).start()
    q.awaitTermination(120)
    want = build(spark.read.schema(C.EVENTS).parquet(folder))
    assert sink.n == want.n_rows() and np.array_equal(sink.total, want.gram())
    sink(spark.read.schema(C.EVENTS).parquet(folder), 0)
    assert sink.n == want.n_rows()


def test_interval_join(spark, folder):
    e = spark.read.schema(C.EVENTS).parquet(folder)
    want = e.alias("a").join(e.alias("b"), F.expr("a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTES")).count()
    drain(C.interval_join(C.read_events(spark, folder), C.read_events(spark, folder)), "ij", "append")
    assert spark.table("ij").count() == want
