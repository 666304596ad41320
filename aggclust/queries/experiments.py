"""Trees, experiments, streams and registered functions as queries."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from aggclust.functions import features as ft
from aggclust.operators import compress as comp
from aggclust.operators import hierarchy as hier
from aggclust.operators import quality
from aggclust.plans import pipeline as pl
from aggclust.plans import workloads as wl
from aggclust.queries.basics import FORMS_SQL, L5, LINE5_SQL, PAIR_SQL, T, nation_pair
from aggclust.sources import points as src

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return keep


def line_points(spark, sf) -> DataFrame:
    return src.line5(T(spark, sf, "lineitem"), ("l_orderkey",)).select(F.col("l_orderkey").alias("id"), F.array(*L5).alias("vec"), F.lit(1.0).alias("w"))


def leaves(spark, sf, **options) -> DataFrame:
    """All rows into at most 1000 entries, over eight trees that meet in two rounds."""
    return comp.compress(line_points(spark, sf), 5, **({"max_leaves": 1000, "partitions": 8, "fan_in": 3, "grid": 4.0} | options))


@query("tree_mass", "SELECT count(*)::DOUBLE AS mass FROM lineitem")
def tree_mass(spark, sf):
    return leaves(spark, sf).agg(F.sum("n").alias("mass"))


@query("tree_total_cf", f"SELECT count(*)::DOUBLE AS n, round(avg(q), 6) AS mu0, round(avg(p), 6) AS mu1, round(count(*) * ({' + '.join(f'var_pop({c})' for c in L5)}) / 1e6, 6) AS sse FROM (SELECT {LINE5_SQL} FROM lineitem)")
def tree_total_cf(spark, sf):
    c = ft.cf_merge_agg(leaves(spark, sf).select(F.lit(1).alias("g"), F.struct("n", "mu", "sse").alias("cf")), ["g"], 5)
    return c.select("cf.n", F.round(F.col("cf.mu")[0], 6).alias("mu0"), F.round(F.col("cf.mu")[1], 6).alias("mu1"), F.round(F.col("cf.sse") / 1e6, 6).alias("sse"))


@query("tree_leaf_bound")
def tree_leaf_bound(spark, sf):
    """Entries of a tree capped at 1000."""
    return leaves(spark, sf).agg(F.count("*").alias("leaves"))


@query("tree_threshold_bound")
def tree_threshold_bound(spark, sf):
    """With the radius as criterion no entry's radius exceeds the final threshold: the largest of both."""
    v = leaves(spark, sf, kind="R", grid=None, dedupe=True, max_leaves=400)
    return v.agg(F.max(F.sqrt(F.col("sse") / F.col("n"))).alias("radius"), F.max("t").alias("threshold"))


@query("tree_fixed_threshold", "SELECT count(*) AS leaves, CAST(max(c) AS DOUBLE) AS heaviest, CAST(0 AS DOUBLE) AS radius FROM (SELECT count(*) AS c FROM part GROUP BY p_size % 20)")
def tree_fixed_threshold(spark, sf):
    """Values a unit apart under a threshold below it: an entry for each value, of radius 0, whatever the order."""
    v = T(spark, sf, "part").select(F.col("p_partkey").alias("id"), F.array((F.col("p_size") % 20).cast("double")).alias("vec"), F.lit(1.0).alias("w"))
    found = comp.compress(v, 1, max_leaves=None, threshold=0.4, kind="D0", partitions=4, fan_in=2)
    return found.agg(F.count("*").alias("leaves"), F.max("n").alias("heaviest"), F.max(F.sqrt(F.col("sse") / F.col("n"))).alias("radius"))


@query("tree_no_compress", "SELECT count(*) AS leaves FROM (SELECT DISTINCT s_acctbal, s_nationkey FROM supplier)")
def tree_no_compress(spark, sf):
    """A cap above the number of distinct rows and threshold 0: every distinct row is an entry."""
    s = T(spark, sf, "supplier").select(F.col("s_suppkey").alias("id"), F.array("s_acctbal", F.col("s_nationkey").cast("double")).alias("vec"), F.lit(1.0).alias("w"))
    return comp.compress(s, 2, max_leaves=100_000, dedupe=True).agg(F.count("*").alias("leaves"))


@query("tree_dedupe", "SELECT count(*) AS n, CAST(sum(c) AS DOUBLE) AS mass, CAST(max(c) AS DOUBLE) AS most FROM (SELECT count(*) AS c FROM lineitem GROUP BY l_quantity, l_discount, l_tax)")
def tree_dedupe(spark, sf):
    v = T(spark, sf, "lineitem").select(F.array("l_quantity", "l_discount", "l_tax").alias("vec"), F.lit(1.0).alias("w"))
    return comp.distinct_points(v).agg(F.count("*").alias("n"), F.sum("n").alias("mass"), F.max("n").alias("most"))


_CELL = ", ".join(f"floor({c} / 10) AS c{i}" for i, c in enumerate(L5))


@query("tree_grid", f"SELECT count(*) AS cells, sum(n)::DOUBLE AS mass, round(sum(sse) / 1e6, 6) AS sse FROM (SELECT count(*) AS n, count(*) * ({' + '.join(f'var_pop({c})' for c in L5)}) AS sse FROM (SELECT {', '.join(L5)}, {_CELL} FROM (SELECT {LINE5_SQL} FROM lineitem)) GROUP BY c0, c1, c2, c3, c4)")
def tree_grid(spark, sf):
    return comp.grid_cells(line_points(spark, sf), 5, 10.0).agg(F.count("*").alias("cells"), F.sum("n").alias("mass"), F.round(F.sum("sse") / 1e6, 6).alias("sse"))


@query("tree_leaves")
def tree_leaves(spark, sf):
    return leaves(spark, sf).select("cf_id", "n", *(F.col("mu")[i].alias(f"mu{i}") for i in range(5)), "sse", "t")


@query("tree_stats")
def tree_stats(spark, sf):
    return comp.tree_stats(leaves(spark, sf))


@query("tree_levels", "SELECT count(*)::DOUBLE AS mass, true AS levels_agree FROM supplier")
def tree_levels(spark, sf):
    """Every inner level of the tree holds the whole mass."""
    s = T(spark, sf, "supplier").select(F.col("s_suppkey").alias("id"), F.array("s_acctbal", F.col("s_nationkey").cast("double")).alias("vec"), F.lit(1.0).alias("w"))
    per = comp.tree_levels(s, 2, width=6).groupBy("level").agg(F.sum("n").alias("mass"))
    return per.agg(F.max("mass").alias("mass"), (F.abs(F.max("mass") - F.min("mass")) < 1e-6).alias("levels_agree"))


@query("rmsd_leaf_vs_points")
def rmsd_leaf_vs_points(spark, sf):
    """RMSD from the entries' features, and RMSD after labelling every point by its nearest entry."""
    p = line_points(spark, sf).withColumn("id", F.monotonically_increasing_id())
    lv = wl.cut_lineage(leaves(spark, sf))
    cut = wl.cut_lineage(hier.cut_k(pl.hierarchy(lv, "cf_aggregation", "chain_linear", kind="D4"), 50))
    a = quality.rmsd(hier.cluster_cfs(lv, cut, 5)).select(F.col("rmsd").alias("by_features"))
    b = quality.rmsd_from_points(p, hier.label_points(comp.assign_to_leaves(p, lv), cut), 5).select(F.col("rmsd").alias("by_points"))
    return a.crossJoin(b)


@query("flagship")
def flagship(spark, sf):
    """Compress all rows, cluster the entries by Ward, cut at 20, and describe the clusters."""
    lv = wl.cut_lineage(leaves(spark, sf))
    cut = hier.cut_k(pl.hierarchy(lv, "cf_linkage", "chain_linear", "ward"), 20)
    c = hier.cluster_cfs(lv, cut, 5)
    return c.select("cluster", "cf.n", *(F.col("cf.mu")[i].alias(f"mu{i}") for i in range(5)), F.sqrt(F.col("cf.sse") / F.col("cf.n")).alias("radius"))


query("w1_runtime")(lambda spark, sf: wl.runtime_and_quality(spark, sf))
query("w4_quality")(lambda spark, sf: wl.quality_over_orders(spark, sf))
query("w3_scaling")(lambda spark, sf: wl.scaling(spark, sf))
query("scaling_slope")(lambda spark, sf: quality.scaling_slope(wl.scaling(spark, sf, sizes=(2500, 5000, 10_000), linkages=("ward",)), ["mode", "linkage"]))
query("speedup")(lambda spark, sf: quality.speedup(wl.scaling(spark, sf, sizes=(10_000,), linkages=("ward",), gen="mix5", cells=wl.TABLE3[3:]), ["gen", "n", "algo"], "full"))
query("w10_cap_sweep")(lambda spark, sf: wl.cap_sweep(spark, sf))
query("w12_exploration")(lambda spark, sf: wl.exploration(spark, sf))


@query("w7_orders")
def w7_orders(spark, sf):
    """Mean and deviation over ten input orders, of the quality and of the number of entries."""
    r = wl.grid(spark, sf, "W7", ["cube5", "mix5"], [2000], list(wl.TABLE3[3:]), ["ward"], 20, [1000], seeds=10)
    leaves = r.groupBy("gen", "mode", "linkage").agg(F.avg("leaves").alias("leaves"))
    return quality.repeated(r, ["gen", "mode", "linkage"], "rmsd").join(leaves, ["gen", "mode", "linkage"])


@query("w5_loss")
def w5_loss(spark, sf):
    return quality.relative_loss(wl.quality_against_size(spark, sf), ["gen", "n", "algo"], "rmsd", "full")


@query("w6_no_compression")
def w6_no_compression(spark, sf):
    """With a cap above the size the compressed run is the full run: the values of both."""
    r = wl.grid(spark, sf, "W6", ["cube5", "mix5"], [600], [wl.TABLE3[0], wl.TABLE3[2]], ["ward"], 20, [1000])
    return r.select("gen", "mode", "leaves", F.round("rmsd", 6).alias("rmsd"))


@query("w8_cut_orders")
def w8_cut_orders(spark, sf):
    """RMSD of Ward by greedy, by a chain cut by height (the same) and by a chain cut in merge order (worse on Gaussians)."""
    return wl.cut_orders(spark, sf).select("algo", F.col("workload").alias("cut_order"), F.round("rmsd", 6).alias("rmsd"))


@query("w9_kmeans")
def w9_kmeans(spark, sf):
    """RMSD of Ward cut at k and of k-means with k centres."""
    return wl.against_kmeans(spark, sf, gen="line5")


# ---- registered functions

def _pairs_view(spark, sf) -> str:
    """A view of the nations' pairs of features, with the functions registered."""
    from aggclust.functions.register import register

    register(spark)
    view = f"nation_pairs_{uuid.uuid4().hex}"
    nation_pair(spark, sf).createOrReplaceTempView(view)
    return view


@query("udf_cf_merge", f"{PAIR_SQL} SELECT k, round(nn, 6) AS n, round((na*a0+nb*b0)/nn, 6) AS mu0, round((na*a1+nb*b1)/nn, 6) AS mu1, round(su, 3) AS sse FROM e")
def udf_cf_merge(spark, sf):
    return spark.sql(f"SELECT k, round(m.n, 6) AS n, round(m.mu[0], 6) AS mu0, round(m.mu[1], 6) AS mu1, round(m.sse, 3) AS sse FROM (SELECT k, cf_merge(a, b) AS m FROM {_pairs_view(spark, sf)})")


@query("sql_distances", f"{PAIR_SQL} SELECT k, {', '.join(f'round({FORMS_SQL[k]}, 6) AS {k.lower()}' for k in FORMS_SQL)} FROM e")
def sql_distances(spark, sf):
    return spark.sql(f"SELECT k, {', '.join(f'round(cf_{k.lower()}(a, b), 6) AS {k.lower()}' for k in FORMS_SQL)} FROM {_pairs_view(spark, sf)}")


@query("udtf_merges", "SELECT s_nationkey AS k, CAST(0 AS INTEGER) AS step, CAST(0 AS INTEGER) AS a, CAST(1 AS INTEGER) AS b, round((max(s_acctbal) - min(s_acctbal)) * (max(s_acctbal) - min(s_acctbal)) / 2, 3) AS height FROM supplier GROUP BY s_nationkey")
def udtf_merges(spark, sf):
    """The merge of each nation's least and greatest account, by the table function."""
    from aggclust.functions.register import register

    register(spark)
    view = f"ends_{uuid.uuid4().hex}"
    T(spark, sf, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.min("s_acctbal").alias("lo"), F.max("s_acctbal").alias("hi")).createOrReplaceTempView(view)
    return spark.sql(f"SELECT v.k, t.step, t.a, t.b, round(t.height, 3) AS height FROM {view} v, LATERAL merge_steps(array(array(v.lo), array(v.hi)), 'D4') t")


@query("agg_full_jaccard")
def agg_full_jaccard(spark, sf):
    """Complete linkage of users by the Jaccard distance of the kinds of their events, as weights."""
    kinds = sorted(r[0] for r in T(spark, sf, "events").select("event_type").distinct().where("event_type IS NOT NULL").collect())
    counts = [F.sum(F.when(F.col("event_type") == k, 1.0).otherwise(0.0)) for k in kinds]
    per = T(spark, sf, "events").where("user_id IS NOT NULL").groupBy("user_id").agg(F.array(*counts).alias("vec"))
    ident = F.row_number().over(Window.orderBy("user_id")).cast("long") - 1  # the users come into one task anyway
    points = per.select(ident.alias("id"), "vec", F.lit(1.0).alias("w"))
    merges = pl.hierarchy(pl.as_items(points), "full", "cached_linear", "complete", base="jaccard", limit=None)
    return merges.select("step", F.least("left", "right").alias("a"), F.greatest("left", "right").alias("b"), F.round("height", 6).alias("height"), "size")
