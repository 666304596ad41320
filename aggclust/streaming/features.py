"""Cluster features over streams: windows, state per key, and a tree kept up to date."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aggclust.functions.features import cf_agg
from aggclust.operators.compress import compress

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
STATE = "n double, mu double, sse double"


def read_events(spark: SparkSession, folder: str, schema: str = EVENTS, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(folder)


def windowed(stream: DataFrame, width: str, slide: str | None = None, late: str = "1 hour", keys: list[str] | None = None, col: str = "value") -> DataFrame:
    """Features per window; rows later than the watermark are dropped and counted by Spark's progress."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return cf_agg(stream.withWatermark("ts", late).withColumn("w", w), [*(keys or []), "w"], [col])


def sessions(stream: DataFrame, gap: str, keys: list[str], late: str = "1 hour", col: str = "value") -> DataFrame:
    return cf_agg(stream.withWatermark("ts", late).withColumn("w", F.session_window("ts", gap)), [*keys, "w"], [col])


def per_key(stream: DataFrame, key: str = "user_id", col: str = "value") -> DataFrame:
    """One feature per key over all rows so far, emitted whenever it changes."""

    def update(key_: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, mu, sse = state.get if state.exists else (0.0, 0.0, 0.0)
        for part in parts:
            x = part["_x"].dropna()
            m = float(len(x))
            if m:
                mean, spread = float(x.mean()), float(((x - x.mean()) ** 2).sum())
                gap, total = mean - mu, n + m
                sse += spread + n * m / total * gap * gap
                mu += gap * m / total
                n = total
        state.update((n, mu, sse))
        yield pd.DataFrame({"key": [key_[0]], "n": [n], "mu": [mu], "sse": [sse]})

    rows = stream.select(F.col(key).cast("long").alias("key"), F.col(col).cast("double").alias("_x"))
    return rows.groupBy("key").applyInPandasWithState(update, f"key long, {STATE}", STATE, "update", "NoTimeout")


def maintain(folder: str, d: int, max_leaves: int, **tree):
    """A ``foreachBatch`` function: compress the batch's points (id, vec, w) and merge its leaves with the stored ones.

    Each epoch writes a version of its own and reads the newest below it, so a repeated epoch
    gives the same version.
    """

    def step(batch: DataFrame, epoch: int) -> None:
        spark = batch.sparkSession
        fresh = compress(batch, d, max_leaves=max_leaves, **tree).select("n", "mu", "sse")
        earlier = [v for v in versions(spark, folder) if v < epoch]
        if earlier:
            fresh = fresh.unionByName(spark.read.parquet(f"{folder}/epoch={max(earlier)}").select("n", "mu", "sse"))
        merged = _again(fresh, d, max_leaves, **tree)
        merged.write.mode("overwrite").parquet(f"{folder}/epoch={epoch}")

    return step


def _again(leaves: DataFrame, d: int, max_leaves: int, **tree) -> DataFrame:
    """One tree over features instead of points."""
    from aggclust.operators.compress import LEAVES, _finish, _local_tree

    options = {"max_leaves": max_leaves, "route": tree.get("kind", "D4"), "width": tree.get("width", 32)}
    one = leaves.repartition(1).sortWithinPartitions("mu", "n", "sse").select("n", "mu", "sse")
    return _finish(one.mapInArrow(_local_tree(d, options), LEAVES))


def versions(spark: SparkSession, folder: str) -> list[int]:
    """Epochs stored so far, listed through Hadoop's file system so that any store will do."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = path.getFileSystem(spark._jsc.hadoopConfiguration())
    if not fs.exists(path):
        return []
    names = [s.getPath().getName() for s in fs.listStatus(path)]
    return sorted(int(n.split("=")[1]) for n in names if n.startswith("epoch=") and fs.exists(spark._jvm.org.apache.hadoop.fs.Path(f"{folder}/{n}/_SUCCESS")))
