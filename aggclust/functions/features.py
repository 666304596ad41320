"""Cluster features as columns: weight, mean vector, sum of squared deviations.

``STRUCT<n DOUBLE, mu ARRAY<DOUBLE>, sse DOUBLE>``.  Merging moves the mean by a share of the gap
between the means and never subtracts large sums, so it stays accurate far from the origin.  The
older feature (weight, sum, sum of squares) is kept beside it as a baseline.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

CF = "struct<n:double,mu:array<double>,sse:double>"
NAIVE = "struct<n:double,ls:array<double>,ss:double>"


def _c(x: str | Column) -> Column:
    return F.col(x) if isinstance(x, str) else x


def cf(n: Column, mu: Column, sse: Column) -> Column:
    return F.struct(n.cast("double").alias("n"), mu.alias("mu"), sse.cast("double").alias("sse"))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def gap(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x - y)


def square_norm(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x * x)


def cf_point(vec: str | Column, weight: str | Column | None = None) -> Column:
    """A (weighted) point: its own mean, no deviation."""
    return cf(F.lit(1.0) if weight is None else _c(weight), _c(vec), F.lit(0.0))


def cf_merge(a: str | Column, b: str | Column) -> Column:
    a, b = _c(a), _c(b)
    n = a["n"] + b["n"]
    share = b["n"] / n
    mu = F.zip_with(a["mu"], b["mu"], lambda x, y: x + (y - x) * share)
    return cf(n, mu, a["sse"] + b["sse"] + a["n"] * share * square_norm(gap(a["mu"], b["mu"])))


def cf_subtract(total: str | Column, part: str | Column) -> Column:
    """What ``part`` leaves of ``total``; null where nothing is left."""
    t, p = _c(total), _c(part)
    n = t["n"] - p["n"]
    mu = F.zip_with(t["mu"], p["mu"], lambda x, y: x + (x - y) * (p["n"] / n))
    sse = F.greatest(F.lit(0.0), t["sse"] - p["sse"] - p["n"] * n / t["n"] * square_norm(gap(p["mu"], mu)))
    return F.when(n > 0, cf(n, mu, sse))


def cf_center(a: str | Column) -> Column:
    return _c(a)["mu"]


def cf_variance(a: str | Column) -> Column:
    return _c(a)["sse"] / _c(a)["n"]


def cf_radius(a: str | Column) -> Column:
    return F.sqrt(cf_variance(a))


def cf_diameter(a: str | Column) -> Column:
    """Root mean squared distance of two different members; 0 for weight up to 1."""
    a = _c(a)
    return F.when(a["n"] > 1, F.sqrt(2 * a["sse"] / (a["n"] - 1))).otherwise(0.0)


def cf_agg(df: DataFrame, keys: list[str], cols: list[str], name: str = "cf") -> DataFrame:
    """The feature of the points of each group, by count, mean and population variance.

    Spark's variance buffer is itself a stable merge with partial aggregation, so only a few
    doubles per group and task are shuffled.
    """
    n = F.count(F.lit(1)).cast("double")
    sse = sum((n * F.var_pop(c) for c in cols[1:]), n * F.var_pop(cols[0]))
    return df.groupBy(*keys).agg(cf(n, F.array(*(F.avg(c) for c in cols)), sse).alias(name))


def cf_merge_agg(df: DataFrame, keys: list[str], d: int, col: str = "cf", strategy: str = "twopass") -> DataFrame:
    """Merge the features of each group.

    ``twopass`` takes the weighted mean first and then the deviations from it, both as plain
    aggregations with map-side combining; ``arrow`` first merges the features of a key within each
    Arrow batch, in NumPy, and does the same with what is left, so only a feature per key and
    batch is shuffled; ``fold`` merges an array of features one by one and suits groups that are
    known to be small.
    """
    c = F.col(col)
    if strategy == "arrow":
        named = [f"`{k}`" for k in keys]
        picked = df.select(*named, c["n"].alias("_n"), c["mu"].alias("_mu"), c["sse"].alias("_sse"))
        partial = picked.mapInArrow(_merged_batches(len(keys), d), picked.schema)
        return cf_merge_agg(partial.select(*named, cf(F.col("_n"), F.col("_mu"), F.col("_sse")).alias(col)), keys, d, col)
    if strategy == "fold":
        merged = F.reduce(F.slice(F.col("_all"), 2, F.size("_all")), F.element_at("_all", 1), cf_merge)
        return df.groupBy(*keys).agg(F.array_sort(F.collect_list(c)).alias("_all")).select(*keys, merged.alias(col))
    if strategy != "twopass":
        raise ValueError(f"unknown strategy {strategy}")
    n = F.sum(c["n"])
    means = df.groupBy(*keys).agg(n.alias("_n"), *(F.sum(c["n"] * c["mu"][i] / 1.0).alias(f"_s{i}") for i in range(d)))
    # Null keys are a group of their own.
    means = means.select(*(F.col(k).alias(f"_k{i}") for i, k in enumerate(keys)), "_n", F.array(*(F.col(f"_s{i}") / F.col("_n") for i in range(d))).alias("_mu"))
    same = [df[k].eqNullSafe(F.col(f"_k{i}")) for i, k in enumerate(keys)]
    joined = df.join(means, same) if keys else df.crossJoin(means)
    spread = joined.groupBy(*keys, "_n", "_mu").agg(F.sum(c["sse"] + c["n"] * square_norm(gap(c["mu"], F.col("_mu")))).alias("_sse"))
    return spread.select(*keys, cf(F.col("_n"), F.col("_mu"), F.col("_sse")).alias(col))


def _merged_batches(keys: int, d: int):
    """A feature per key and batch from rows (keys, n, mu, sse)."""

    def run(batches):
        import numpy as np
        import pyarrow as pa

        for b in batches:
            if not len(b):
                continue
            code = np.zeros(len(b), np.int64)
            for i in range(keys):
                values = b.column(i).dictionary_encode(null_encoding="encode").indices.to_numpy(zero_copy_only=False).astype(np.int64)
                _, code = np.unique(code * (values.max() + 1) + values, return_inverse=True)
            _, first = np.unique(code, return_index=True)
            n, sse = (b.column(keys + i).to_numpy(zero_copy_only=False) for i in (0, 2))
            mu = b.column(keys + 1).flatten().to_numpy(zero_copy_only=False).reshape(len(b), d)
            total = np.bincount(code, weights=n)
            mean = np.stack([np.bincount(code, weights=n * x) / total for x in mu.T], 1)
            spread = np.bincount(code, weights=sse + n * ((mu - mean[code]) ** 2).sum(1))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(total) + 1) * d, pa.int32()), pa.array(mean.reshape(-1)))
            yield pa.RecordBatch.from_arrays([*(b.column(i).take(pa.array(first)) for i in range(keys)), pa.array(total), lists, pa.array(spread)], names=b.schema.names)

    return run


def naive_agg(df: DataFrame, keys: list[str], cols: list[str], name: str = "nf") -> DataFrame:
    ss = sum((F.sum(F.col(c) * F.col(c)) for c in cols[1:]), F.sum(F.col(cols[0]) * F.col(cols[0])))
    body = F.struct(F.count(F.lit(1)).cast("double").alias("n"), F.array(*(F.sum(c) for c in cols)).alias("ls"), ss.alias("ss"))
    return df.groupBy(*keys).agg(body.alias(name))


def naive_merge(a: str | Column, b: str | Column) -> Column:
    a, b = _c(a), _c(b)
    return F.struct((a["n"] + b["n"]).alias("n"), F.zip_with(a["ls"], b["ls"], lambda x, y: x + y).alias("ls"), (a["ss"] + b["ss"]).alias("ss"))


def naive_sse(a: str | Column) -> Column:
    return _c(a)["ss"] - square_norm(_c(a)["ls"]) / _c(a)["n"]


def stability_gap(df: DataFrame, cols: list[str], shift: float) -> DataFrame:
    """Deviations of the whole table, as it is and moved by ``shift``, by either feature."""
    moved = df.select(*(F.col(c).cast("double").alias(c) for c in cols), *((F.col(c).cast("double") + shift).alias(f"_{c}") for c in cols))
    stable = [cf_agg(moved, [], c).select(F.col("cf.sse").alias("stable_sse")) for c in (cols, [f"_{c}" for c in cols])]
    naive = [naive_agg(moved, [], c).select(naive_sse("nf").alias("naive_sse")) for c in (cols, [f"_{c}" for c in cols])]
    rows = [s.crossJoin(v).withColumn("shift", F.lit(x)) for s, v, x in zip(stable, naive, (0.0, float(shift)))]
    return rows[0].unionByName(rows[1])
