"""Clustering from points to a hierarchy: input modes, searches and which of them go together."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from aggclust.functions import linkage as link
from aggclust.functions.cfdist import KINDS, squared_matrix
from aggclust.operators import agglomerate as agg
from aggclust.operators.compress import CAP, compress

MODES = ("full", "cf_centers", "cf_linkage", "cf_aggregation")
SEARCHES = ("scan", "cached", "chain_matrix", "chain_linear", "cached_linear")
MERGES = "step int, left long, right long, node long, height double, size double"
COUNTED = f"{MERGES}, distances long, cells long, peak_bytes long"
#: Items that one task takes; searches with a matrix are limited further, by its bytes.
FULL_LIMIT = 60_000
LINEAR = ("chain_linear", "cached_linear")
GEOMETRIC = {"upgmc": ("D0", 1.0), "ward": ("D4", 2.0), "upgma": ("D2", 1.0)}


def validate(mode: str, search: str, linkage: str | None, kind: str | None, base: str = "euclidean") -> None:
    """Raise ValueError for a combination that has no meaning."""
    if mode not in MODES or search not in SEARCHES:
        raise ValueError(f"modes are {MODES}, searches {SEARCHES}")
    if mode == "cf_aggregation":
        if kind not in KINDS:
            raise ValueError(f"cf_aggregation takes a feature distance of {KINDS}")
        return
    if linkage in link.BY_DEFINITION:
        if mode != "full" or search != "scan":
            raise ValueError(f"{linkage} needs all distances of the points: mode full, search scan")
        return
    found = link.get(linkage or "")
    if mode == "cf_linkage":
        if found.cf_kind is None:
            raise ValueError(f"{linkage} has no distance of features")
        if search in LINEAR and linkage not in ("upgmc", "ward"):
            raise ValueError("linear memory needs a linkage that follows from weights and means")
    elif search == "cached_linear" and mode == "full" and linkage == "complete":
        return
    elif search in LINEAR and (linkage not in GEOMETRIC or (linkage == "upgma" and base != "sqeuclidean")):
        raise ValueError("linear memory needs a geometric linkage")


def solve(n: np.ndarray, mu: np.ndarray, sse: np.ndarray, mode: str, search: str, linkage: str | None = None, kind: str | None = None, base: str = "euclidean", cut_order: str = "height", counters=None) -> list[tuple]:
    """Numbered merges of items in memory; heights are squared wherever the linkage is."""
    validate(mode, search, linkage, kind, base)
    if mode == "cf_aggregation":
        return agg.number(agg.agglomerate_cf(n, mu, sse, kind, search, counters), n, cut_order)
    if mode in ("full", "cf_centers"):
        n, sse = np.ones(len(n)), np.zeros(len(n))
    if linkage in link.BY_DEFINITION:
        return agg.number(agg.greedy_definition(agg.point_matrix(mu, base), linkage, counters), n, cut_order)
    found = link.get(linkage)
    squared = found.squared or base == "sqeuclidean" or mode == "cf_linkage"
    if search == "cached_linear" and linkage == "complete":
        return agg.number(agg.complete_linear(mu, base, squared, counters), n, cut_order)
    if search in LINEAR and linkage in ("ward", "upgmc"):
        run = agg.chain_centres if search == "chain_linear" else agg.greedy_centres
        return agg.number(run(n, mu, linkage, counters), n, cut_order)
    if search in LINEAR:
        feature, factor = GEOMETRIC[linkage]
        run = agg.greedy_linear if search == "cached_linear" else agg.chain_linear
        return agg.number([(i, j, h * factor) for i, j, h in run(n, mu, sse, feature, counters)], n, cut_order)
    if search == "scan":
        d = squared_matrix(found.cf_kind, n, mu, sse) * found.cf_factor if mode == "cf_linkage" else agg.point_matrix(mu, base, squared)
        return agg.number(agg.greedy_scan(d, n, linkage, counters), n, cut_order)
    d = agg.condensed_features(found.cf_kind, n, mu, sse, found.cf_factor) if mode == "cf_linkage" else agg.condensed_points(mu, base, squared)
    run = {"cached": agg.greedy_cached, "chain_matrix": agg.chain_matrix}[search]
    return agg.number(run(d, n, linkage, counters), n, cut_order)


def _arrays(table: pa.Table) -> tuple:
    table = table.combine_chunks()
    order = np.argsort(table["cf_id"].to_numpy(), kind="stable")
    flat = table["mu"].combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(float)
    mu = flat.reshape(len(table), -1) if len(table) else flat
    return table["cf_id"].to_numpy()[order], table["n"].to_numpy()[order], (mu[order] if len(mu) else np.zeros((0, 1))), table["sse"].to_numpy()[order]


def merges_batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64())
    cols = list(zip(*rows)) or [()] * 6
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], names=["step", "left", "right", "node", "height", "size"])


def hierarchy(items: DataFrame, mode: str, search: str, linkage: str | None = None, kind: str | None = None, base: str = "euclidean", cut_order: str = "height", limit: int | None = FULL_LIMIT) -> DataFrame:
    """The merge table of items (cf_id 0.., n, mu, sse), built in one task.

    The stages before stay parallel: the items are brought together by a shuffle of their own.
    More than ``limit`` items, or a matrix beyond its limit, raise, so an uncompressed table cannot
    end up in one task, and the search that was asked for is the one that runs.  No ``limit`` is for
    searches in linear memory whose items must all be taken.
    """
    return counted(items, mode, search, linkage, kind, base, cut_order, limit).drop("distances", "cells", "peak_bytes")


def counted(items: DataFrame, mode: str, search: str, linkage: str | None = None, kind: str | None = None, base: str = "euclidean", cut_order: str = "height", limit: int | None = FULL_LIMIT) -> DataFrame:
    """The same, and in every row what the run evaluated and held: distances, matrix cells, peak bytes."""
    validate(mode, search, linkage, kind, base)

    def run(batches):
        got = [b for b in batches if len(b)]
        if not got:
            return
        if limit is not None and sum(map(len, got)) > limit:
            raise ValueError(f"more than {limit} items: compress first")
        _, n, mu, sse = _arrays(pa.Table.from_batches(got))
        counters = agg.Counters()
        out = merges_batch(solve(n, mu, sse, mode, search, linkage, kind, base, cut_order, counters))
        values = (counters.distances, counters.cells, counters.peak_bytes)
        yield pa.RecordBatch.from_arrays([*out.columns, *(pa.array([v] * len(out), pa.int64()) for v in values)], names=[*out.schema.names, "distances", "cells", "peak_bytes"])

    return items.select("cf_id", "n", "mu", "sse").repartition(1).mapInArrow(run, COUNTED)


def as_items(points: DataFrame) -> DataFrame:
    """Points (id 0.., vec, w) as features."""
    return points.select(F.col("id").alias("cf_id"), F.col("w").alias("n"), F.col("vec").alias("mu"), F.lit(0.0).alias("sse"))


def cluster(points: DataFrame, d: int, mode: str = "cf_linkage", search: str = "chain_matrix", linkage: str | None = "ward", kind: str | None = None, max_leaves: int = CAP, base: str = "euclidean", cut_order: str = "height", **tree) -> tuple[DataFrame, DataFrame]:
    """Items and merge table: points themselves in mode ``full``, else the leaves of a tree of at most ``max_leaves``."""
    validate(mode, search, linkage, kind, base)
    if mode == "full":
        items = as_items(points)
    else:
        route = kind or link.get(linkage).cf_kind or "D0"
        items = compress(points, d, max_leaves=max_leaves, kind=tree.pop("route", route), **tree)
    return items, hierarchy(items, mode, search, linkage, kind, base, cut_order)


def agglomerate_by(features: DataFrame, keys: list[str], mode: str, search: str, linkage: str | None = None, kind: str | None = None) -> DataFrame:
    """A hierarchy per key of features (keys, cf_id, n, mu, sse); each group must fit the limit of one task."""
    validate(mode, search, linkage, kind)
    schema = features.select(*keys).schema.simpleString()[len("struct<") : -1]

    def run(key, pdf):
        import pandas as pd

        if len(pdf) > FULL_LIMIT:
            raise ValueError(f"more than {FULL_LIMIT} items in a group: compress first")
        pdf = pdf.sort_values("cf_id")
        rows = solve(pdf["n"].to_numpy(float), np.stack(pdf["mu"].to_numpy()).astype(float), pdf["sse"].to_numpy(float), mode, search, linkage, kind)
        out = pd.DataFrame(rows, columns=["step", "left", "right", "node", "height", "size"])
        for name, value in zip(keys, key):
            out[name] = value
        return out

    typed = ", ".join(f"{p.split(':')[0]} {p.split(':')[1]}" for p in schema.split(","))
    return features.groupBy(*keys).applyInPandas(run, f"{MERGES}, {typed}")
