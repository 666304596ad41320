"""The experiments, re-expressed on the given tables: run records as DataFrames."""

from __future__ import annotations

import time
from functools import lru_cache
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aggclust.functions.features import cf_agg
from aggclust.operators import agglomerate as agg
from aggclust.operators import hierarchy as hier
from aggclust.operators import quality
from aggclust.operators.cftree import CFTree
from aggclust.operators.compress import compress
from aggclust.plans import pipeline as pl
from aggclust.sources import points as src
from aggclust.sources.storage import cut_lineage

RECORD = (
    "workload string, gen string, n long, algo string, search string, mode string, linkage string, seed int, k int, cap int, "
    "ms long, tree_ms long, leaves long, rmsd double, distances long, cells long, peak_bytes long"
)
#: The measured pairs of algorithm and input: name, search, mode.
TABLE3 = (
    ("row-nearest", "cached", "full"), ("row-nearest", "cached", "cf_centers"), ("row-nearest", "cached", "cf_linkage"),
    ("chain", "chain_linear", "full"), ("chain", "chain_linear", "cf_aggregation"), ("chain", "chain_linear", "cf_linkage"),
)
#: The pairs whose quality is compared.
TABLE4 = tuple(TABLE3[i] for i in (0, 2, 3, 5))
KINDS = {"ward": "D4", "upgmc": "D0", "upgma": "D2"}


def chosen(search: str, mode: str, n: int) -> str:
    """The row-nearest search on full data keeps no matrix where that would pass the limit; records name what ran."""
    return "cached_linear" if search == "cached" and mode == "full" and 4 * n * (n - 1) > agg.MATRIX_BYTES else search


def offered(search: str, mode: str, linkage: str) -> bool:
    return not (search == "chain_linear" and linkage == "upgma")


def generated(spark: SparkSession, sf_dir: str, gen: str, n: int) -> DataFrame:
    """The first ``n`` points (id 0.., vec, w) in hash order of a generator on lineitem.

    Ids are numbered in a window over the chosen rows only, which the experiments bound.
    """
    from pyspark.sql import Window

    li = src.table(spark, sf_dir, "lineitem").withColumn("_h", src.row_hash())
    rows = li.orderBy("_h", "l_orderkey", "l_partkey", "l_linenumber", "l_extendedprice").limit(n)
    if gen == "line5":
        v, cols = src.line5(rows, ("_h",)), src.LINE5
    elif gen == "cube5":
        v, cols = src.cube5(rows, keep=("_h",)), src.CUBE5
    elif gen == "mix5":
        v, cols = src.mix5(rows, keep=("_h",)), src.MIX5
    else:
        raise ValueError(f"unknown generator {gen}")
    ident = F.row_number().over(Window.orderBy("_h", *cols)).cast("long") - 1
    return v.select(ident.alias("id"), F.array(*cols).alias("vec"), F.lit(1.0).alias("w"))


def shuffled(points: DataFrame, seed: int) -> DataFrame:
    """The same points with ids in another order: one of the repeated input orders."""
    from pyspark.sql import Window

    ident = F.row_number().over(Window.orderBy(F.xxhash64(F.lit(seed), "id"), "id")).cast("long") - 1
    return points.select(ident.alias("id"), "vec", "w")


def run(points: DataFrame, d: int, search: str, mode: str, linkage: str, k: int, cap: int, seed: int = 0, cut_order: str = "height", base: str | None = None) -> dict:
    """One run through the DataFrame operators: total and tree milliseconds, items, RMSD of k clusters, counters."""
    base = base or ("sqeuclidean" if linkage == "upgma" else "euclidean")
    began = time.perf_counter()
    if mode == "full":
        items = pl.as_items(points)
    else:
        items = compress(points, d, max_leaves=cap, kind=KINDS[linkage], partitions=1, seed=seed)
    items = cut_lineage(items.select("cf_id", "n", "mu", "sse"))
    tree = time.perf_counter()
    kind = KINDS[linkage] if mode == "cf_aggregation" else None
    found = cut_lineage(pl.counted(items, mode, search, None if kind else linkage, kind, base, cut_order))
    merges = found.drop("distances", "cells", "peak_bytes")
    value = quality.rmsd(hier.cluster_cfs(items, hier.cut_k(merges, k), d)).first()
    done = time.perf_counter()
    held = found.agg(F.count("*").alias("merges"), *(F.max(c).alias(c) for c in ("distances", "cells", "peak_bytes"))).first()
    return {
        "ms": int((done - began) * 1000), "tree_ms": int((tree - began) * 1000), "leaves": held["merges"] + 1, "rmsd": float(value["rmsd"]),
        "distances": held["distances"], "cells": held["cells"], "peak_bytes": held["peak_bytes"],
    }


def records(spark: SparkSession, sf_dir: str, workload: str, gens: list[str], sizes: list[int], cells: list[tuple], linkages: list[str], k: int | None, cap: int, seeds: int = 1, cut_order: str = "height") -> DataFrame:
    """A run record per generator, size, algorithm, linkage and input order, one after the other, as times are compared."""
    rows = []
    for gen in gens:
        for n in sizes:
            points = cut_lineage(generated(spark, sf_dir, gen, n))
            for seed in range(seeds):
                order = cut_lineage(shuffled(points, seed)) if seeds > 1 else points
                for algo, search, mode in cells:
                    for linkage in linkages:
                        if offered(search, mode, linkage):
                            use, many = chosen(search, mode, n), k or max(1, n // 100)
                            r = run(order, 5, use, mode, linkage, many, cap, seed, cut_order)
                            rows.append((workload, gen, n, algo, use, mode, linkage, seed, many, cap, *(r[c] for c in ("ms", "tree_ms", "leaves", "rmsd", "distances", "cells", "peak_bytes"))))
    return spark.createDataFrame(rows, RECORD)


def solved(x: np.ndarray, w: np.ndarray, search: str, mode: str, linkage: str, k: int, cap: int, seed: int, cut_order: str = "height") -> dict:
    """One run on points in memory, in a seeded order."""
    began = time.perf_counter()
    order = np.random.default_rng(seed).permutation(len(x))
    n, mu, sse = w[order], x[order], np.zeros(len(x))
    if mode != "full":
        tree = CFTree(x.shape[1], max_leaves=cap, route=KINDS[linkage])
        tree.insert_many(n, mu, sse)
        n, mu, sse = tree.leaves()
    built = time.perf_counter()
    counters = agg.Counters()
    kind = KINDS[linkage] if mode == "cf_aggregation" else None
    merges = pl.solve(n, mu, sse, mode, search, None if kind else linkage, kind, "sqeuclidean" if linkage == "upgma" else "euclidean", cut_order, counters)
    _, label = np.unique(agg.cut(merges, len(n), k), return_inverse=True)
    total = np.bincount(label, weights=n)
    centre = np.stack([np.bincount(label, weights=n * c) / total for c in mu.T], 1)
    spread = float(sse.sum() + (n * ((mu - centre[label]) ** 2).sum(1)).sum())
    done = time.perf_counter()
    return {
        "ms": int((done - began) * 1000), "tree_ms": int((built - began) * 1000), "leaves": len(n), "rmsd": float(np.sqrt(spread / n.sum())),
        "distances": counters.distances, "cells": counters.cells, "peak_bytes": counters.peak_bytes,
    }


def grid(spark: SparkSession, sf_dir: str, workload: str, gens: list[str], sizes: list[int], cells: list[tuple], linkages: list[str], k: int | None, caps: list[int], seeds: int = 1, cut_order: str = "height") -> DataFrame:
    """The records of ``records`` for measures that do not depend on other runs: every run is a task, all at once.

    Runs and points meet in a join, so a task gets its points by one shuffle and the driver none.
    """
    runs = []
    for gen in gens:
        for n in sizes:
            for algo, search, mode in cells:
                for linkage in linkages:
                    for cap in caps if mode != "full" else caps[:1]:
                        for seed in range(seeds):
                            if offered(search, mode, linkage):
                                runs.append((workload, gen, n, algo, chosen(search, mode, n), mode, linkage, seed, k or max(1, n // 100), cap))
    names = [c.split(" ")[0] for c in RECORD.split(", ")]
    plan = spark.createDataFrame([(i, *r) for i, r in enumerate(runs)], "run int, " + ", ".join(RECORD.split(", ")[:10]))
    points = None
    for gen in gens:
        for n in sizes:
            part = generated(spark, sf_dir, gen, n).select(F.lit(gen).alias("gen"), F.lit(n).cast("long").alias("n"), "id", "vec", "w")
            points = part if points is None else points.unionByName(part)

    def work(table: pa.Table) -> pa.Table:
        table = table.combine_chunks().sort_by("id").combine_chunks()
        one = {c: table[c][0].as_py() for c in names[:10]}
        x = table["vec"].combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(table), -1)
        got = solved(x, table["w"].to_numpy().astype(float), one["search"], one["mode"], one["linkage"], one["k"], one["cap"], one["seed"], cut_order)
        kinds = {"string": pa.string(), "int": pa.int32(), "long": pa.int64(), "double": pa.float64()}
        types = [kinds[c.split(" ")[1]] for c in RECORD.split(", ")]
        return pa.table([pa.array([(one | got)[c]], t) for c, t in zip(names, types)], names=names)

    met = points.join(F.broadcast(plan), ["gen", "n"])
    # One partition for each run: a run is long, its points are few.
    return cut_lineage(met.repartition(len(runs), "run").groupBy("run").applyInArrow(work, RECORD))


def runtime_and_quality(spark, sf_dir, n=10_000, cap=5000, linkages=("ward",), gens=("cube5", "mix5"), seeds=1, k=None) -> DataFrame:
    """W1, W2: all measured pairs on uniform and Gaussian points, one after the other."""
    return records(spark, sf_dir, "W1", list(gens), [n], list(TABLE3), list(linkages), k, cap, seeds)


def quality_over_orders(spark, sf_dir, n=3000, cap=1500, seeds=10, k=None) -> DataFrame:
    """W4: mean and deviation of the RMSD over input orders, both generators and all linkages."""
    r = grid(spark, sf_dir, "W4", ["cube5", "mix5"], [n], list(TABLE4), ["upgmc", "upgma", "ward"], k, [cap], seeds)
    return quality.repeated(r, ["gen", "algo", "mode", "linkage"], "rmsd")


def scaling(spark, sf_dir, sizes=(2500, 5000, 10_000, 20_000), cap=2500, linkages=("ward", "upgmc"), gen="line5", cells=(TABLE3[3], TABLE3[5])) -> DataFrame:
    """W3: full and compressed time against size."""
    return records(spark, sf_dir, "W3", [gen], list(sizes), list(cells), list(linkages), 20, cap)


def quality_against_size(spark, sf_dir, sizes=(2500, 5000, 10_000), cap=2500, k=100) -> DataFrame:
    """W5, and W6 at the size that the cap does not reach: there both modes agree."""
    return grid(spark, sf_dir, "W5", ["cube5", "mix5"], list(sizes), [TABLE3[0], TABLE3[2], TABLE3[3], TABLE3[5]], ["upgmc"], k, [cap])


def cut_orders(spark, sf_dir, n=1000, k=20) -> DataFrame:
    """W8: how a chain's cut in merge order differs from the cut by height, against greedy."""
    greedy = grid(spark, sf_dir, "height", ["mix5"], [n], [TABLE3[0], TABLE3[3]], ["ward"], k, [0])
    return greedy.unionByName(grid(spark, sf_dir, "merge", ["mix5"], [n], [TABLE3[3]], ["ward"], k, [0], cut_order="merge"))


def cap_sweep(spark, sf_dir, caps=(500, 1000, 2500, 5000, 10_000), n=20_000, k=100) -> DataFrame:
    """W10: a smaller cap is faster and coarser."""
    return grid(spark, sf_dir, "W10", ["line5"], [n], [TABLE3[5]], ["ward"], k, list(caps))


def against_kmeans(spark, sf_dir, gen="mix5", n=1000, k=20, seed=1) -> DataFrame:
    """W9: Ward cut at k against k-means with k centres, on the same points."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    points = cut_lineage(generated(spark, sf_dir, gen, n))
    ward = run(points, 5, "chain_linear", "full", "ward", k, 0)["rmsd"]
    vectors = points.select("id", array_to_vector("vec").alias("features"), *(F.col("vec")[i].alias(f"x{i}") for i in range(5)))
    # Several starts, as a single one may end in a poor optimum.
    best = None
    for s in range(3):
        labels = KMeans(k=k, seed=seed + s, maxIter=40).fit(vectors).transform(vectors)
        value = quality.rmsd(cf_agg(labels, ["prediction"], [f"x{i}" for i in range(5)])).first()["rmsd"]
        best = value if best is None else min(best, value)
    return spark.createDataFrame([("ward", float(ward)), ("kmeans", float(best))], "method string, rmsd double")


def bags(docs: DataFrame, d: int = 32) -> DataFrame:
    """id and vec of documents (k, text): percent of the words in each of ``d`` hash buckets."""

    def run(batches):
        bucket = lru_cache(65_536)(lambda word: crc32(word.encode()) % d)
        for b in batches:
            counts = [np.bincount([bucket(w) for w in (t or "").split()], minlength=d) for t in b.column(1).to_pylist()]
            vec = [(c * (100 / max(1, c.sum()))).tolist() for c in counts]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(vec, pa.list_(pa.float64()))], names=["id", "vec"])

    return docs.select(F.col("k").cast("long").alias("k"), "text").mapInArrow(run, "id long, vec array<double>")


def exploration(spark, sf_dir, cap=1000, partitions=8) -> DataFrame:
    """W12: the points, and the heights' spread, of hierarchies of other tables, each compressed as a whole."""
    t = lambda name: src.table(spark, sf_dir, name)
    ends = lambda df, *cols: df.select(F.col("k").cast("long").alias("id"), F.array(*(F.coalesce(F.col(c).cast("double"), F.lit(0.0)) for c in cols)).alias("vec"))
    roles = ("user", "assistant", "system")
    chars = [F.sum(F.when(F.col("role") == r, F.length("text") / 100)).alias(r) for r in roles]
    other = F.sum(F.when(~F.coalesce(F.col("role").isin(*roles), F.lit(False)), F.length("text") / 100)).alias("other")
    frames = {
        "nations": (ends(t("customer").groupBy(F.col("c_nationkey").alias("k")).agg(F.avg("c_acctbal").alias("a"), F.count("*").alias("b")), "a", "b"), 2),
        "suppliers": (ends(t("supplier").select(F.col("s_suppkey").alias("k"), (F.col("s_acctbal") / 100).alias("a"), F.col("s_nationkey").alias("b")), "a", "b"), 2),
        "users": (ends(t("events").groupBy(F.col("user_id").alias("k")).agg(F.avg("value").alias("a"), F.count("*").alias("b")), "a", "b"), 2),
        "parts": (ends(t("part").select(F.col("p_partkey").alias("k"), F.col("p_size").alias("a"), (F.col("p_retailprice") / 100).alias("b")), "a", "b"), 2),
        "pages": (ends(t("pages").select(F.col("page_id").alias("k"), F.length("url").alias("a"), (F.length("html") / 100).alias("b")), "a", "b"), 2),
        "embeddings": (t("embeddings").select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").cast("array<double>").alias("vec")), 64),
        "documents": (bags(t("documents").select(F.col("doc_id").alias("k"), "text")), 32),
        "conversations": (ends(t("conversations").groupBy(F.col("conv_id").alias("k")).agg(*chars, other), *roles, "other"), 4),
    }
    out = None
    for name, (points, d) in frames.items():
        items = cut_lineage(compress(points.withColumn("w", F.lit(1.0)), d, max_leaves=cap, kind="D4", partitions=partitions).select("cf_id", "n", "mu", "sse"))
        m = pl.hierarchy(items, "cf_linkage", "chain_linear", "ward").agg(F.count("*").alias("merges"), F.max("height").alias("top"), F.expr("percentile_approx(height, 0.5)").alias("median"))
        m = m.crossJoin(items.agg(F.sum("n").alias("points"))).select(F.lit(name).alias("table"), "*")
        out = m if out is None else out.unionByName(m)
    return out


def brute_rmsd(x: np.ndarray, labels: np.ndarray) -> float:
    return float(np.sqrt(sum(((x[labels == c] - x[labels == c].mean(0)) ** 2).sum() for c in np.unique(labels)) / len(x)))
