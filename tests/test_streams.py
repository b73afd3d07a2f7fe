"""Streams against their batch forms; late rows."""

import datetime as dt

from pyspark.sql import functions as F

from hypernear.streaming import flows


def test_late_rows_are_dropped(spark, tmp_path):
    at = lambda h: dt.datetime(2024, 1, 1, tzinfo=dt.timezone.utc) + dt.timedelta(hours=h)
    folder = str(tmp_path / "in")
    for batch in ([(at(0), 1.0), (at(10), 2.0)], [(at(11), 3.0)], [(at(1), 9.0), (at(12), 4.0)], [(at(30), 5.0)]):
        spark.createDataFrame(batch, "ts timestamp, margin double").coalesce(1).write.mode("append").parquet(folder)
    stream = spark.readStream.schema("ts timestamp, margin double").option("maxFilesPerTrigger", 1).parquet(folder)
    out = flows.drained(flows.windowed(stream, "2 hours"), spark, "late_test").collect()
    # The row of hour 1 comes after hour 10 was seen, beyond the delay of one hour.
    assert {r.least for r in out} >= {1.0, 2.0} and 9.0 not in {r.least for r in out}
    assert sum(r.n for r in out) <= 4


def test_running_topk_equals_batch(spark, tmp_path):
    folder = str(tmp_path / "in")
    for part in range(3):
        spark.range(part * 50, part * 50 + 50).select((F.col("id") % 2).alias("qid"), "id", ((F.col("id") * 37) % 101 / 101.0).alias("margin")).coalesce(1).write.mode("append").parquet(folder)
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    stream = spark.readStream.schema("qid long, id long, margin double").option("maxFilesPerTrigger", 1).parquet(folder)
    out = flows.drained(flows.running_topk(stream, 3), spark, "topk_test", "update").groupBy("qid", "rank").agg(F.min("margin").alias("m")).collect()
    batch = spark.read.parquet(folder).collect()
    for q in (0, 1):
        want = sorted(r.margin for r in batch if r.qid == q)[:3]
        assert [r.m for r in sorted(out) if r.qid == q] == want


def test_stream_join_in_time(spark, tmp_path):
    at = lambda m: dt.datetime(2024, 1, 1, tzinfo=dt.timezone.utc) + dt.timedelta(minutes=m)
    a, b = str(tmp_path / "a"), str(tmp_path / "b")
    spark.createDataFrame([(at(50), 1, [2.0, 1.0]), (at(300), 1, [3.0, 1.0])], "ts timestamp, key long, x array<double>").write.parquet(a)
    spark.createDataFrame([(at(10), 1, [1.0, 0.0]), (at(60), 1, [1.0, -1.0])], "plane_ts timestamp, plane_key long, q array<double>").write.parquet(b)
    points = spark.readStream.schema("ts timestamp, key long, x array<double>").parquet(a)
    planes = spark.readStream.schema("plane_ts timestamp, plane_key long, q array<double>").parquet(b)
    out = flows.drained(flows.matched(points, planes), spark, "join_test").collect()
    assert [r.margin for r in out] == [2.0]


def test_a_restarted_stream_goes_on_from_its_checkpoint(spark, tmp_path):
    """A second run with the first one's checkpoint reads only what is new, and keeps its state."""
    folder, checkpoint = str(tmp_path / "in"), str(tmp_path / "checkpoint")
    add = lambda start: spark.range(start, start + 10).select(F.lit(0).cast("long").alias("qid"), "id", (F.col("id") / 100).alias("margin")).coalesce(1).write.mode("append").parquet(folder)
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    run = lambda: flows.drained(flows.running_topk(spark.readStream.schema("qid long, id long, margin double").parquet(folder), 3), spark, "restart_test", "update", checkpoint).collect()
    add(10)
    assert sorted(r.id for r in run()) == [10, 11, 12]
    add(50)
    assert run() == []  # nothing nearer: the state of the first run is still there
    add(0)
    assert sorted(r.id for r in run()) == [0, 1, 2]
