"""Operators on merge tables (step, left, right, node, height, size) over items 0..m-1."""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from aggclust.functions.features import cf_merge_agg
from aggclust.operators import agglomerate as agg
from aggclust.operators.compress import CAP

_COLS = ("step", "left", "right", "node", "height", "size")


def _in_task(merges: DataFrame, work, schema: str) -> DataFrame:
    """``work`` on the whole, sorted merge table, in one task; merge tables are bounded by the tree's cap."""

    def run(batches):
        rows = [r for b in batches for r in zip(*(c.to_pylist() for c in b.columns))]
        cols = work(rows)
        kinds = {"int": pa.int32(), "long": pa.int64(), "double": pa.float64(), "string": pa.string()}
        spec = [p.strip().split(" ") for p in schema.split(",")]
        yield pa.RecordBatch.from_arrays([pa.array(c, kinds[t]) for c, (_, t) in zip(cols, spec)], names=[n for n, _ in spec])

    return merges.select(*_COLS).repartition(1).sortWithinPartitions("step").mapInArrow(run, schema)


def cut_k(merges: DataFrame, k: int) -> DataFrame:
    """item, cluster after all but the last k - 1 merges; a cluster is named by its smallest item."""

    def work(rows):
        m = len(rows) + 1
        return np.arange(m), agg.cut(rows, m, k)

    return _in_task(merges, work, "item long, cluster long")


def cut_height(merges: DataFrame, height: float) -> DataFrame:
    """item, cluster joined by the merges up to ``height``."""

    def work(rows):
        m = len(rows) + 1
        low = [r for r in rows if r[4] <= height]
        return np.arange(m), agg.cut(low, m, m - len(low))

    return _in_task(merges, work, "item long, cluster long")


def sweep_k(merges: DataFrame, ks: list[int]) -> DataFrame:
    """k, item, cluster for several k from one scan of the hierarchy."""

    def work(rows):
        m = len(rows) + 1
        cuts = [agg.cut(rows, m, k) for k in ks]
        return np.repeat(ks, m), np.tile(np.arange(m), len(ks)), np.concatenate(cuts) if cuts else np.zeros(0, np.int64)

    return _in_task(merges, work, "k int, item long, cluster long")


def label_points(assigned: DataFrame, labels: DataFrame) -> DataFrame:
    """id, cluster from (id, cf_id) and (item, cluster).

    Labels are sent to all tasks if they are at most ``CAP``, which is counted; else the join shuffles.
    """
    few = labels.limit(CAP + 1).count() <= CAP
    return assigned.join(F.broadcast(labels) if few else labels, F.col("cf_id") == F.col("item")).select("id", "cluster")


def inversions(merges: DataFrame) -> DataFrame:
    """Merges lower than one of their parts: step, height, part, part_height."""
    parts = merges.select(F.col("node").alias("part"), F.col("height").alias("part_height"))
    both = merges.select("step", "height", F.explode(F.array("left", "right")).alias("part"))
    return both.join(parts, "part").where("height < part_height").select("step", "height", "part", "part_height")


def members(merges: DataFrame, node: int) -> DataFrame:
    """The items below a node."""
    view = f"_merges_{uuid.uuid4().hex}"
    merges.createOrReplaceTempView(view)
    return merges.sparkSession.sql(
        f"""WITH RECURSIVE below(id) AS (
            SELECT CAST({int(node)} AS BIGINT) AS id
            UNION ALL
            SELECT explode(array(left, right)) AS id FROM below JOIN {view} ON node = id)
        SELECT id AS item FROM below WHERE id NOT IN (SELECT node FROM {view})"""
    )


def _sets(rows: list[tuple]) -> dict[int, list[int]]:
    m = len(rows) + 1
    own = {i: [i] for i in range(m)}
    for _, left, right, node, *_ in rows:
        own[node] = own[left] + own[right]
    return own


def cophenetic(merges: DataFrame) -> DataFrame:
    """i < j and the height at which they meet; the output is quadratic in the items."""

    def work(rows):
        own = _sets(rows)
        i, j, h = [], [], []
        for _, left, right, _, height, _ in rows:
            a, b = np.array(own[left]), np.array(own[right])
            x, y = np.repeat(a, len(b)), np.tile(b, len(a))
            i.append(np.minimum(x, y))
            j.append(np.maximum(x, y))
            h.append(np.full(len(x), height))
        flat = lambda p, t: np.concatenate(p) if p else np.zeros(0, t)
        return flat(i, np.int64), flat(j, np.int64), flat(h, float)

    return _in_task(merges, work, "i long, j long, height double")


def merge_overlap(one: DataFrame, two: DataFrame) -> DataFrame:
    """How many clusters of more than one item both hierarchies form."""

    def work(rows):
        own = _sets(rows)
        return ([",".join(map(str, sorted(own[r[3]]))) for r in rows],)

    a, b = (_in_task(m, work, "members string").distinct() for m in (one, two))
    return a.intersect(b).agg(F.count("*").alias("shared"))


def cluster_cfs(items: DataFrame, labels: DataFrame, d: int) -> DataFrame:
    """cluster and its feature, from items (cf_id, n, mu, sse) and (item, cluster)."""
    joined = items.join(labels, F.col("cf_id") == F.col("item")).select("cluster", F.struct("n", "mu", "sse").alias("cf"))
    return cf_merge_agg(joined, ["cluster"], d)
