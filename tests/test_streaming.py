"""Streamed features against their batch twins."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from aggclust.functions.features import cf_agg
from aggclust.streaming import features as stream


@pytest.fixture()
def slices(spark, tmp_path):
    start = dt.datetime(2024, 1, 1)
    rows = [(i, start + dt.timedelta(minutes=7 * i), i % 5, "t", float(i % 13), "{}") for i in range(300)]
    for k in range(3):
        spark.createDataFrame(rows[k * 100 : (k + 1) * 100], stream.EVENTS).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    return f"{tmp_path}/in", rows


def collect(query, name, spark):
    query.processAllAvailable()
    query.stop()
    return spark.sql(f"SELECT * FROM {name}")


def test_windows_equal_the_batch(spark, slices, tmp_path):
    folder, _ = slices
    s = stream.windowed(stream.read_events(spark, folder, per_trigger=10), "6 hours")
    out = collect(s.writeStream.outputMode("complete").format("memory").queryName("w6").start(), "w6", spark)
    batch = cf_agg(spark.read.parquet(folder).withColumn("w", F.window("ts", "6 hours")), ["w"], ["value"])
    flat = lambda d: sorted((r[0].start, r[1].n, round(r[1].sse, 6)) for r in d.select("w", "cf").collect())
    assert flat(out) == flat(batch)


def test_state_per_key_ends_as_the_batch(spark, slices):
    folder, _ = slices
    out = collect(stream.per_key(stream.read_events(spark, folder)).writeStream.outputMode("update").format("memory").queryName("pk").start(), "pk", spark)
    last = {r.key: r for r in out.orderBy("n").collect()}
    for r in cf_agg(spark.read.parquet(folder), ["user_id"], ["value"]).collect():
        assert (last[r.user_id].n, last[r.user_id].mu, last[r.user_id].sse) == pytest.approx((r.cf.n, r.cf.mu[0], r.cf.sse))


def test_a_tree_is_kept_across_epochs(spark, slices, tmp_path):
    folder, rows = slices
    points = stream.read_events(spark, folder).select(F.col("event_id").alias("id"), F.array("value", F.col("user_id").cast("double")).alias("vec"), F.lit(1.0).alias("w"))
    step = stream.maintain(f"{tmp_path}/tree", 2, 40)
    q = points.writeStream.foreachBatch(step).option("checkpointLocation", f"{tmp_path}/state").start()
    q.processAllAvailable()
    q.stop()
    seen = stream.versions(spark, f"{tmp_path}/tree")
    last = spark.read.parquet(f"{tmp_path}/tree/epoch={max(seen)}")
    assert len(seen) >= 2 and last.agg(F.sum("n")).first()[0] == len(rows) and last.count() <= 40
    before = sorted(map(tuple, last.collect()))
    step(spark.read.parquet(folder).where("event_id < 0").select(F.col("event_id").alias("id"), F.array("value", "value").alias("vec"), F.lit(1.0).alias("w")), max(seen) + 1)
    again = spark.read.parquet(f"{tmp_path}/tree/epoch={max(seen) + 1}")
    assert again.agg(F.sum("n")).first()[0] == len(rows) and sorted(map(tuple, spark.read.parquet(f"{tmp_path}/tree/epoch={max(seen)}").collect())) == before


def test_late_rows_are_dropped_behind_the_watermark(spark, tmp_path):
    start = dt.datetime(2024, 1, 1)
    row = lambda i, h: (i, start + dt.timedelta(hours=h), 1, "t", 1.0, "{}")
    write = lambda rows: spark.createDataFrame(rows, stream.EVENTS).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    write([row(1, 0), row(2, 30)])
    s = stream.windowed(stream.read_events(spark, f"{tmp_path}/in"), "1 hour", late="1 hour")
    q = s.writeStream.outputMode("append").format("memory").queryName("late").option("checkpointLocation", f"{tmp_path}/ck").start()
    q.processAllAvailable()
    write([row(3, 0), row(4, 60)])
    q.processAllAvailable()
    write([row(5, 90)])
    q.processAllAvailable()
    q.stop()
    got = {r.w.start.hour + 24 * (r.w.start.day - 1): r.cf.n for r in spark.sql("SELECT * FROM late").collect()}
    assert got.get(0) == 1.0
