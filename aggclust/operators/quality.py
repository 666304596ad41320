"""Measures of partitions and of runs."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from aggclust.functions.features import cf_agg


def rmsd(clusters: DataFrame, col: str = "cf", d: int | None = None) -> DataFrame:
    """Root of the clusters' summed squares over their summed weights; with ``d`` per dimension."""
    c = F.col(col)
    return clusters.agg(F.sqrt(F.sum(c["sse"]) / F.sum(c["n"]) / (d or 1)).alias("rmsd"), F.count("*").alias("k"))


def rmsd_from_points(points: DataFrame, labels: DataFrame, d: int) -> DataFrame:
    """The same from points (id, vec) and labels (id, cluster)."""
    flat = points.join(labels, "id").select("cluster", *(F.col("vec")[i].alias(f"x{i}") for i in range(d)))
    return rmsd(cf_agg(flat, ["cluster"], [f"x{i}" for i in range(d)]))


def wss(clusters: DataFrame, col: str = "cf") -> DataFrame:
    return clusters.agg(F.sum(F.col(col)["sse"]).alias("wss"))


def adjusted_rand(labels: DataFrame, a: str, b: str) -> DataFrame:
    """Adjusted Rand index of two partitions of the same rows, from their contingency counts."""
    pairs = lambda x: x * (x - 1) / 2
    cells = labels.groupBy(a, b).agg(F.count("*").alias("c"))
    both = cells.agg(F.sum(pairs(F.col("c"))).alias("both"), F.sum("c").alias("n"))
    one = cells.groupBy(a).agg(F.sum("c").alias("c")).agg(F.sum(pairs(F.col("c"))).alias("one"))
    two = cells.groupBy(b).agg(F.sum("c").alias("c")).agg(F.sum(pairs(F.col("c"))).alias("two"))
    chance = F.col("one") * F.col("two") / pairs(F.col("n"))
    top = (F.col("one") + F.col("two")) / 2
    score = F.when(top == chance, 1.0).otherwise((F.col("both") - chance) / (top - chance))
    return both.crossJoin(one).crossJoin(two).select(score.alias("ari"))


def timed(work: Callable) -> tuple[object, float]:
    began = time.perf_counter()
    out = work()
    return out, (time.perf_counter() - began) * 1000


def repeated(runs: DataFrame, keys: list[str], value: str) -> DataFrame:
    """Mean and sample deviation over repetitions."""
    return runs.groupBy(*keys).agg(F.avg(value).alias("mean"), F.stddev_samp(value).alias("sd"), F.count("*").alias("runs"))


def relative_loss(runs: DataFrame, keys: list[str], value: str, baseline: str) -> DataFrame:
    """Each mode's value over that of mode ``baseline`` with the same keys, minus one."""
    base = runs.where(F.col("mode") == baseline).groupBy(*keys).agg(F.avg(value).alias("_base"))
    return runs.groupBy(*keys, "mode").agg(F.avg(value).alias("mean")).join(base, keys).select(*keys, "mode", "mean", (F.col("mean") / F.col("_base") - 1).alias("loss"))


def speedup(runs: DataFrame, keys: list[str], baseline: str) -> DataFrame:
    loss = relative_loss(runs, keys, "ms", baseline)
    return loss.select(*keys, "mode", (1 / (F.col("loss") + 1)).alias("speedup"))


def scaling_slope(runs: DataFrame, keys: list[str]) -> DataFrame:
    """Slope of log time over log size."""
    return runs.groupBy(*keys).agg(F.regr_slope(F.log("ms"), F.log("n")).alias("slope"))
