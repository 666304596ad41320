"""Compression of points into a bounded number of features, tree by tree.

Partitions build trees of their own; their leaf entries, which are features and can be inserted
like points, meet in groups of ``fan_in`` trees per round until one tree is left.  Only entries
are shuffled: at most the cap per tree, whatever the table's size.  Each entry carries its tree's
final threshold, and a later tree goes on with the largest that it has received.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from aggclust.functions.features import cf_agg
from aggclust.operators.cftree import CFTree
from aggclust.sources.storage import cut_lineage

LEAVES = "part int, pos long, t double, rebuilds int, depth int, inserted long, n double, mu array<double>, sse double"
CAP, FAN_IN = 25_000, 16


def _rows(tree: CFTree, part: int, inserted: int, rebuilds: int) -> pa.RecordBatch:
    n, mu, sse = tree.leaves()
    m = len(n)
    full = lambda v, t: pa.array([v] * m, t)
    return pa.RecordBatch.from_arrays(
        [
            full(part, pa.int32()),
            pa.array(range(m), pa.int64()),
            full(tree.threshold, pa.float64()),
            full(rebuilds + tree.rebuilds, pa.int32()),
            full(tree.depth, pa.int32()),
            full(inserted, pa.int64()),
            pa.array(n, pa.float64()),
            pa.ListArray.from_arrays(pa.array(np.arange(m + 1) * tree.d, pa.int32()), pa.array(mu.reshape(-1), pa.float64())),
            pa.array(sse, pa.float64()),
        ],
        names=["part", "pos", "t", "rebuilds", "depth", "inserted", "n", "mu", "sse"],
    )


def _features(batch: pa.RecordBatch, d: int, n: str = "n", mu: str = "mu", sse: str = "sse") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Weights, means (m, d) and sums of squares of an Arrow batch, without Python rows."""
    flat = batch.column(mu).flatten().to_numpy(zero_copy_only=False).astype(float, copy=False)
    return batch.column(n).to_numpy(zero_copy_only=False), flat.reshape(len(batch), d), batch.column(sse).to_numpy(zero_copy_only=False)


def _local_tree(d: int, options: dict):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tree = CFTree(d, **options)
        for b in batches:
            if len(b):
                tree.insert_many(*_features(b, d))
        if tree.inserted:
            yield _rows(tree, TaskContext.get().partitionId(), tree.inserted, 0)

    return run


def _merge_round(d: int, options: dict):
    """Entries come sorted by group, and within it by part and position; one tree per group.

    Nothing but the tree and a batch is held, however many trees meet.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now = tree = None
        part, inserted, rebuilds = None, 0, 0
        for b in batches:
            groups, parts = (b.column(c).to_numpy() for c in ("grp", "part"))
            ends = np.flatnonzero(np.diff(groups)) + 1
            for lo, hi in zip([0, *ends], [*ends, len(b)]):
                if lo == hi:
                    continue
                if groups[lo] != now:
                    if tree is not None:
                        yield _rows(tree, now, inserted, rebuilds)
                    now, tree, part, inserted, rebuilds = int(groups[lo]), CFTree(d, **options), None, 0, 0
                piece = b.slice(lo, hi - lo)
                # Each part's counters stand in all its rows: they count once.
                for at in [lo, *(np.flatnonzero(np.diff(parts[lo:hi])) + lo + 1)]:
                    if parts[at] != part:
                        part = parts[at]
                        inserted += b.column("inserted")[at].as_py()
                        rebuilds += b.column("rebuilds")[at].as_py()
                tree.raise_to(max(piece.column("t").to_numpy()))
                tree.insert_many(*_features(piece, d))
        if tree is not None:
            yield _rows(tree, now, inserted, rebuilds)

    return run


def permute(points: DataFrame, seed: int, partitions: int) -> DataFrame:
    """A reproducible input order: rows dealt and sorted by a seeded hash, then by content."""
    key = F.xxhash64(F.lit(seed), "id", "vec", "w")
    return points.withColumn("_h", key).repartition(partitions, "_h").sortWithinPartitions("_h", "id", "vec", "w").drop("_h")


def grid_cells(points: DataFrame, d: int, eps: float) -> DataFrame:
    """Features of grid cells of side ``eps``, in built-in aggregation alone; a cell's spread is at most eps * sqrt(d)."""
    x = points.select("w", *(F.col("vec")[i].alias(f"x{i}") for i in range(d)))
    cells = [F.floor(F.col(f"x{i}") / eps).alias(f"c{i}") for i in range(d)]
    return cf_agg(x.select("*", *cells), [f"c{i}" for i in range(d)], [f"x{i}" for i in range(d)]).select("cf.*")


def distinct_points(points: DataFrame) -> DataFrame:
    """Exact duplicates as one weighted point."""
    return points.groupBy("vec").agg(F.sum("w").alias("n")).select("n", F.col("vec").alias("mu"), F.lit(0.0).alias("sse"))


def compress(
    points: DataFrame,
    d: int,
    max_leaves: int | None = CAP,
    kind: str = "D4",
    absorb: str | None = None,
    threshold: float = 0.0,
    partitions: int = 1,
    seed: int = 0,
    fan_in: int = FAN_IN,
    order: str = "hash",
    dedupe: bool = False,
    grid: float | None = None,
    width: int = 32,
    growth: str = "mean",
) -> DataFrame:
    """Leaf features (cf_id, n, mu, sse, t and the counters rebuilds, depth, inserted) of points (id, vec, w).

    ``order='hash'`` deals rows by a seeded hash, so results do not depend on the cluster;
    ``'scan'`` keeps the scan's splits and moves no row.
    """
    options = {"threshold": threshold, "max_leaves": max_leaves, "route": kind, "absorb": absorb, "width": width, "growth": growth}
    if grid:
        feats = grid_cells(points, d, grid)
    elif dedupe:
        feats = distinct_points(points)
    else:
        feats = None
    if feats is not None:
        h = F.xxhash64(F.lit(seed), "mu")
        src = feats.withColumn("_h", h).repartition(partitions, "_h").sortWithinPartitions("_h", "mu", "n").select("n", "mu", "sse") if order == "hash" else feats
    else:
        src = permute(points, seed, partitions) if order == "hash" else points.sortWithinPartitions("id", "vec", "w")
        src = src.select(F.col("w").alias("n"), F.col("vec").alias("mu"), F.lit(0.0).alias("sse"))
    trees = src.mapInArrow(_local_tree(d, options), LEAVES)
    count = partitions
    if order == "scan":
        # The entries are written once; which parts there are says how many rounds are needed.
        trees = cut_lineage(trees)
        count = (trees.agg(F.max("part")).first()[0] or 0) + 1
    while count > 1:
        groups = math.ceil(count / fan_in)
        dealt = trees.withColumn("grp", (F.col("part") / fan_in).cast("int")).repartition(groups, "grp").sortWithinPartitions("grp", "part", "pos")
        trees = dealt.select("grp", "part", "pos", "t", "rebuilds", "inserted", "n", "mu", "sse").mapInArrow(_merge_round(d, options), LEAVES)
        count = groups
    return _finish(trees)


def _finish(trees: DataFrame) -> DataFrame:
    """Number the entries by content in the one task that holds them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = 0
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array(range(at, at + len(b)), pa.int64()), *b.columns], names=["cf_id", *b.schema.names])
            at += len(b)

    one = trees.select("n", "mu", "sse", "t", "rebuilds", "depth", "inserted").repartition(1).sortWithinPartitions("mu", "n", "sse")
    return one.mapInArrow(run, "cf_id long, n double, mu array<double>, sse double, t double, rebuilds int, depth int, inserted long")


def tree_stats(leaves: DataFrame) -> DataFrame:
    return leaves.agg(F.count("*").alias("leaves"), F.max("rebuilds").alias("rebuilds"), F.max("t").alias("threshold"), F.max("depth").alias("depth"), F.max("inserted").alias("inserted"))


def tree_levels(points: DataFrame, d: int, **options) -> DataFrame:
    """The nodes of one tree over all of ``points`` (in one task, so for bounded inputs)."""

    def run(batches):
        tree = CFTree(d, **options)
        for b in batches:
            if len(b):
                flat = b.column(0).flatten().to_numpy(zero_copy_only=False)
                tree.insert_points(flat.reshape(len(b), d), b.column(1).to_numpy(zero_copy_only=False))
        cols = list(zip(*tree.levels()))
        kinds = (pa.int64(), pa.int64(), pa.int32(), pa.bool_(), pa.float64(), pa.list_(pa.float64()), pa.float64())
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], names=["node_id", "parent_id", "level", "is_leaf", "n", "mu", "sse"])

    one = permute(points, options.pop("seed", 0), 1)
    return one.select("vec", "w").mapInArrow(run, "node_id long, parent_id long, level int, is_leaf boolean, n double, mu array<double>, sse double")


def assign_to_leaves(points: DataFrame, leaves: DataFrame, cap: int = CAP) -> DataFrame:
    """id and cf_id of the nearest leaf centre, for every point; the leaves are sent to all tasks.

    Leaves are bounded by the tree's cap, which is checked before they are sent.
    """
    rows = leaves.select("cf_id", "mu").orderBy("cf_id").limit(cap + 1).collect()
    if len(rows) > cap:
        raise ValueError(f"more than {cap} leaves")
    ids = np.array([r[0] for r in rows], np.int64)
    centres = np.array([r[1] for r in rows], float).T
    norms = (centres * centres).sum(0)

    def run(batches):
        for b in batches:
            x = b.column(1).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(b), -1)
            best = np.concatenate([ids[(norms - 2 * (x[i : i + 1024] @ centres)).argmin(1)] for i in range(0, len(x), 1024)]) if len(x) else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(best, pa.int64())], names=["id", "cf_id"])

    return points.select("id", "vec").mapInArrow(run, "id long, cf_id long")
