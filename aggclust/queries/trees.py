"""Hierarchies of the nations' features, held against recursive SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from aggclust.functions import cfdist, linkage as link
from aggclust.operators import hierarchy as hier
from aggclust.operators import quality, rounds
from aggclust.plans import pipeline as pl
from aggclust.queries.basics import NATION2, T, nation_cf2

QUERIES: dict = {}
SQL: dict[str, str] = {}
M = 25  # nations; merged clusters are numbered from here

_RECURRENCE = {
    "single": "least(x.d, y.d)", "complete": "greatest(x.d, y.d)", "upgma": "(b.ni * x.d + b.nj * y.d) / (b.ni + b.nj)", "wpgma": "(x.d + y.d) / 2",
    "upgmc": "(b.ni * x.d + b.nj * y.d) / (b.ni + b.nj) - b.ni * b.nj * b.d / ((b.ni + b.nj) * (b.ni + b.nj))", "wpgmc": "(x.d + y.d) / 2 - b.d / 4",
    "ward": "((b.ni + x.nk) * x.d + (b.nj + x.nk) * y.d - x.nk * b.d) / (b.ni + b.nj + x.nk)",
}
_FORM = {
    "D0": "{g}", "D1": "pow(abs(u.m0 - v.m0) + abs(u.m1 - v.m1), 2)", "D2": "u.sse / u.n + v.sse / v.n + {g}",
    "D3": "CASE WHEN u.n + v.n > 1 THEN 2 * (u.sse + v.sse + u.n * v.n / (u.n + v.n) * {g}) / (u.n + v.n - 1) ELSE 0 END",
    "D4": "u.n * v.n / (u.n + v.n) * {g}", "R": "(u.sse + v.sse + u.n * v.n / (u.n + v.n) * {g}) / (u.n + v.n)",
}
_G = "((u.m0 - v.m0) * (u.m0 - v.m0) + (u.m1 - v.m1) * (u.m1 - v.m1))"


def by_recurrence(items: str, seed: str, name: str) -> str:
    """CTEs ending in ``merges``: the live pairs are the working table, one merge per step.

    ``items`` selects k, n, m0, m1, sse; ``seed`` is the distance of u and v.
    """
    return f"""WITH RECURSIVE items AS ({items}),
pairs(step, i, j, d, ni, nj) AS (
  SELECT 0, u.k, v.k, {seed}, u.n, v.n FROM items u JOIN items v ON u.k < v.k
  UNION ALL
  SELECT * FROM (
    WITH b AS (SELECT step, i, j, d, ni, nj FROM pairs ORDER BY d, i, j LIMIT 1),
    ends AS (SELECT CASE WHEN p.i IN (b.i, b.j) THEN p.j ELSE p.i END AS k, CASE WHEN p.i IN (b.i, b.j) THEN p.nj ELSE p.ni END AS nk,
        (p.i = b.i OR p.j = b.i) AS to_i, p.d FROM pairs p, b WHERE (p.i IN (b.i, b.j)) <> (p.j IN (b.i, b.j)))
    SELECT p.step + 1, p.i, p.j, p.d, p.ni, p.nj FROM pairs p, b WHERE p.i NOT IN (b.i, b.j) AND p.j NOT IN (b.i, b.j)
    UNION ALL
    SELECT b.step + 1, x.k, {M} + b.step, {_RECURRENCE[name]}, x.nk, b.ni + b.nj FROM b, ends x JOIN ends y ON x.k = y.k AND x.to_i AND NOT y.to_i)),
merges AS (SELECT step, i AS "left", j AS "right", {M} + step AS node, d AS height, ni + nj AS size FROM (
  SELECT *, row_number() OVER (PARTITION BY step ORDER BY d, i, j) AS r FROM pairs) WHERE r = 1)
"""


def by_features(items: str, kind: str) -> str:
    """CTEs ending in ``merges``: the live features are the working table."""
    d = _FORM[kind].format(g=_G)
    pick = f"SELECT u.step, u.k AS i, v.k AS j, {d} AS d, u.n AS ni, v.n AS nj, u.m0 AS a0, u.m1 AS a1, u.sse AS sa, v.m0 AS b0, v.m1 AS b1, v.sse AS sb FROM live u JOIN live v ON u.step = v.step AND u.k < v.k"
    return f"""WITH RECURSIVE live(step, k, n, m0, m1, sse) AS (
  SELECT 0, k, n, m0, m1, sse FROM ({items})
  UNION ALL
  SELECT * FROM (
    WITH b AS ({pick} ORDER BY d, i, j LIMIT 1)
    SELECT l.step + 1, l.k, l.n, l.m0, l.m1, l.sse FROM live l, b WHERE l.k NOT IN (b.i, b.j)
    UNION ALL
    SELECT step + 1, {M} + step, ni + nj, a0 + (b0 - a0) * nj / (ni + nj), a1 + (b1 - a1) * nj / (ni + nj),
      sa + sb + ni * nj / (ni + nj) * ((b0 - a0) * (b0 - a0) + (b1 - a1) * (b1 - a1)) FROM b)),
merges AS (SELECT step, i AS "left", j AS "right", {M} + step AS node, d AS height, ni + nj AS size FROM (
  SELECT *, row_number() OVER (PARTITION BY step ORDER BY d, i, j) AS r FROM ({pick})) WHERE r = 1)
"""


# Merges are compared by what they join, in SQL as in Spark: node numbers agree where the order of
# heights does, which holds for everything registered with SQL here.
_OUT = 'SELECT CAST(step AS BIGINT) AS step, least("left", "right")::BIGINT AS a, greatest("left", "right")::BIGINT AS b, round(height, 5) AS height, round(size, 5) AS size FROM merges'


def out(merges: DataFrame) -> DataFrame:
    return merges.select(F.col("step").cast("long").alias("step"), F.least("left", "right").alias("a"), F.greatest("left", "right").alias("b"), F.round("height", 5).alias("height"), F.round("size", 5).alias("size"))


def items(spark, sf) -> DataFrame:
    return nation_cf2(spark, sf).select(F.col("k").cast("long").alias("cf_id"), "cf.n", "cf.mu", "cf.sse")


def tree(spark, sf, mode: str, search: str, linkage: str | None = None, kind: str | None = None, cut_order: str = "merge") -> DataFrame:
    return pl.hierarchy(items(spark, sf), mode, search, linkage, kind, cut_order=cut_order)


_ONES = f"SELECT k, CAST(1 AS DOUBLE) AS n, m0, m1, CAST(0 AS DOUBLE) AS sse FROM ({NATION2})"


def _add(name: str, sql: str, f) -> None:
    QUERIES[name], SQL[name] = f, sql + _OUT


for _n, _l in link.LINKAGES.items():
    _add(f"agg_full_{_n}", by_recurrence(_ONES, _G if _l.squared else f"sqrt{_G}", _n), lambda spark, sf, n=_n: out(tree(spark, sf, "full", "scan", n)))
for _n in ("ward", "upgmc", "upgma"):
    _l = link.LINKAGES[_n]
    _add(f"agg_centers_{_n}", by_recurrence(_ONES, _G if _l.squared else f"sqrt{_G}", _n), lambda spark, sf, n=_n: out(tree(spark, sf, "cf_centers", "cached", n)))
for _n in ("upgma", "wpgma", "upgmc", "wpgmc", "ward"):
    _l = link.LINKAGES[_n]
    _add(f"agg_linkage_{_n}", by_recurrence(NATION2, f"{_l.cf_factor} * ({_FORM[_l.cf_kind].format(g=_G)})", _n), lambda spark, sf, n=_n: out(tree(spark, sf, "cf_linkage", "cached", n)))
for _k in cfdist.KINDS:
    _add(f"agg_aggregation_{_k.lower()}", by_features(NATION2, _k), lambda spark, sf, k=_k: out(tree(spark, sf, "cf_aggregation", "scan", kind=k)))

WARD = by_features(NATION2, "D4")
for _n, _s in (("agg_chain_ward", "chain_linear"), ("agg_chain_matrix_ward", "chain_matrix"), ("agg_cached_ward", "cached")):
    _add(_n, WARD, lambda spark, sf, s=_s: out(tree(spark, sf, "cf_aggregation", s, kind="D4", cut_order="height")))
# Chains on distances that are not reducible depend on the order of the items: no SQL.
for _k in ("D0", "D1", "D3", "R"):
    QUERIES[f"agg_chain_{_k.lower()}"] = lambda spark, sf, k=_k: out(tree(spark, sf, "cf_aggregation", "chain_linear", kind=k, cut_order="height"))
for _n in ("upgmc", "wpgmc"):
    QUERIES[f"agg_chain_{_n}"] = lambda spark, sf, n=_n: out(tree(spark, sf, "cf_linkage", "chain_matrix", n, cut_order="height"))


def _node_pairs(spark, sf) -> DataFrame:
    c = items(spark, sf).select("cf_id", F.struct("n", "mu", "sse").alias("cf"))
    a, b = c.select(F.col("cf_id").alias("i"), F.col("cf").alias("a")), c.select(F.col("cf_id").alias("j"), F.col("cf").alias("b"))
    return a.join(b, F.col("i") < F.col("j")).select("i", "j", (2 * cfdist.cf_distance("a", "b", "D4", squared=True)).alias("d"))


def agg_rounds_ward(spark, sf) -> DataFrame:
    """Heights and sizes of all merges, by rounds of mutual nearest neighbours."""
    sizes = items(spark, sf).select(F.col("cf_id").alias("id"), "n")
    found = rounds.reciprocal_rounds(_node_pairs(spark, sf), sizes, "ward")
    return found.select(F.round("height", 5).alias("height"), F.round("size", 5).alias("size"))


QUERIES["agg_rounds_ward"], SQL["agg_rounds_ward"] = agg_rounds_ward, WARD + "SELECT round(2 * height, 5) AS height, round(size, 5) AS size FROM merges"


def agg_forest_single(spark, sf) -> DataFrame:
    return rounds.single_by_forest(_node_pairs(spark, sf)).select(F.round("d", 5).alias("height"))


QUERIES["agg_forest_single"] = agg_forest_single
SQL["agg_forest_single"] = by_recurrence(NATION2, f"2 * ({_FORM['D4'].format(g=_G)})", "single") + "SELECT round(height, 5) AS height FROM merges"


def agg_by_region(spark, sf) -> DataFrame:
    """A hierarchy per region: the largest height and the number of merges."""
    n = T(spark, sf, "nation").select(F.col("n_nationkey").cast("long").alias("cf_id"), F.col("n_regionkey").alias("region"))
    per = pl.agglomerate_by(items(spark, sf).join(n, "cf_id"), ["region"], "cf_aggregation", "chain_linear", kind="D4")
    return per.groupBy("region").agg(F.count("*").alias("merges"), F.round(F.sum("height"), 3).alias("heights"))


QUERIES["agg_by_region"] = agg_by_region
# The heights of D4 add up to the growth of the sum of squares from the parts to the whole.
SQL["agg_by_region"] = f"""WITH f AS ({NATION2}), g AS (SELECT n_regionkey AS region, f.* FROM f JOIN nation ON k = n_nationkey),
t AS (SELECT region, sum(n) AS nn, sum(n * m0) / sum(n) AS c0, sum(n * m1) / sum(n) AS c1 FROM g GROUP BY region)
SELECT region, count(*) - 1 AS merges, round(sum(n * ((m0 - c0) * (m0 - c0) + (m1 - c1) * (m1 - c1))), 3) AS heights FROM g JOIN t USING (region) GROUP BY region"""


_MODES = (("upgma", "D2", 1.0), ("upgmc", "D0", 1.0), ("ward", "D4", 2.0))


def agg_mode_agreement(spark, sf) -> DataFrame:
    """The summed heights by aggregation and by linkage, where a linkage has an exact distance of features."""
    out = None
    for name, kind, factor in _MODES:
        a = tree(spark, sf, "cf_aggregation", "scan", kind=kind).agg(F.round(F.sum("height") * factor, 3).alias("aggregation"))
        b = tree(spark, sf, "cf_linkage", "scan", name).agg(F.round(F.sum("height"), 3).alias("linkage_sum"))
        row = a.crossJoin(b).select(F.lit(name).alias("linkage"), "aggregation", "linkage_sum")
        out = row if out is None else out.unionByName(row)
    return out


QUERIES["agg_mode_agreement"] = agg_mode_agreement
SQL["agg_mode_agreement"] = " UNION ALL ".join(
    f"SELECT '{n}' AS linkage, (SELECT * FROM ({by_features(NATION2, k)} SELECT round(sum(height) * {f}, 3) FROM merges)) AS aggregation, "
    f"(SELECT * FROM ({by_recurrence(NATION2, f'{link.LINKAGES[n].cf_factor} * ({_FORM[k].format(g=_G)})', n)} SELECT round(sum(height), 3) FROM merges)) AS linkage_sum"
    for n, k, f in _MODES
)

# Linkages by definition alone, on the nations' centres: no recurrence, hence no SQL.
for _n in link.BY_DEFINITION:
    QUERIES[f"agg_full_{_n}"] = lambda spark, sf, n=_n: out(tree(spark, sf, "full", "scan", n))


def seed_mismatch(spark, sf) -> DataFrame:
    """Merges whose cluster is not formed when Ward is seeded with plain distances."""
    right = tree(spark, sf, "full", "scan", "ward")
    import numpy as np

    from aggclust.operators import agglomerate as agg

    def wrong(batches):
        import pyarrow as pa

        got = [b for b in batches if len(b)]
        _, _, mu, _ = pl._arrays(pa.Table.from_batches(got))
        yield pl.merges_batch(agg.number(agg.greedy_scan(agg.point_matrix(mu), np.ones(len(mu)), "ward"), np.ones(len(mu)), "merge"))

    other = items(spark, sf).select("cf_id", "n", "mu", "sse").repartition(1).mapInArrow(wrong, pl.MERGES)
    return hier.merge_overlap(right, other).select((F.lit(M - 1) - F.col("shared")).alias("changed"))


QUERIES["seed_mismatch"] = seed_mismatch

# ---- operators on the Ward tree

_CUT = WARD + f""", low AS (SELECT * FROM merges WHERE step < {M} - 5),
up(item, node) AS (SELECT k::BIGINT, k::BIGINT FROM ({NATION2}) UNION ALL SELECT item, CAST(low.node AS BIGINT) FROM up JOIN low ON up.node IN (low."left", low."right")),
top AS (SELECT item, max(node) AS node FROM up GROUP BY item),
labels AS (SELECT item, min(item) OVER (PARTITION BY node) AS cluster FROM top)
"""


def ward(spark, sf) -> DataFrame:
    return tree(spark, sf, "cf_aggregation", "chain_linear", kind="D4", cut_order="height")


QUERIES["cut_k"], SQL["cut_k"] = lambda spark, sf: hier.cut_k(ward(spark, sf), 5), _CUT + "SELECT item, cluster FROM labels"
QUERIES["cut_height"], SQL["cut_height"] = lambda spark, sf: hier.cut_height(ward(spark, sf), 3.0), _CUT.replace(f"step < {M} - 5", "height <= 3") + "SELECT item, cluster FROM labels"
QUERIES["inversions"] = lambda spark, sf: hier.inversions(tree(spark, sf, "cf_aggregation", "scan", kind="D0")).select(F.col("step").cast("long").alias("step"), F.round("height", 5).alias("height"), "part", F.round("part_height", 5).alias("part_height"))
SQL["inversions"] = by_features(NATION2, "D0") + 'SELECT CAST(m.step AS BIGINT) AS step, round(m.height, 5) AS height, CAST(p.node AS BIGINT) AS part, round(p.height, 5) AS part_height FROM merges m JOIN merges p ON p.node IN (m."left", m."right") WHERE m.height < p.height'
QUERIES["members"] = lambda spark, sf: hier.members(ward(spark, sf), 2 * M - 4)
SQL["members"] = WARD + f""", below(id) AS (SELECT {2 * M - 4}::BIGINT UNION ALL SELECT unnest([m."left"::BIGINT, m."right"::BIGINT]) FROM below JOIN merges m ON m.node = below.id)
SELECT id AS item FROM below WHERE id < {M}"""
QUERIES["cophenetic"] = lambda spark, sf: hier.cophenetic(ward(spark, sf)).select("i", "j", F.round("height", 5).alias("height"))
SQL["cophenetic"] = WARD + f""", up(item, node, height) AS (SELECT k::BIGINT, k::BIGINT, CAST(0 AS DOUBLE) FROM ({NATION2}) UNION ALL SELECT item, CAST(m.node AS BIGINT), m.height FROM up JOIN merges m ON up.node IN (m."left", m."right"))
SELECT a.item AS i, b.item AS j, round(min(a.height), 5) AS height FROM up a JOIN up b ON a.node = b.node AND a.item < b.item GROUP BY a.item, b.item"""


def _clusters(spark, sf, k: int = 5) -> DataFrame:
    return hier.cluster_cfs(items(spark, sf), hier.cut_k(ward(spark, sf), k), 2)


_PER = _CUT + f", f AS ({NATION2}), c AS (SELECT cluster, sum(n) AS n, sum(n * m0) / sum(n) AS m0, sum(n * m1) / sum(n) AS m1 FROM f JOIN labels ON k = item GROUP BY cluster), s AS (SELECT l.cluster, c.n, c.m0, c.m1, sum(f.sse + f.n * ((f.m0 - c.m0) * (f.m0 - c.m0) + (f.m1 - c.m1) * (f.m1 - c.m1))) AS sse FROM f JOIN labels l ON f.k = l.item JOIN c ON c.cluster = l.cluster GROUP BY ALL) "
QUERIES["cluster_cfs"] = lambda spark, sf: _clusters(spark, sf).select("cluster", F.round("cf.n", 5).alias("n"), F.round(F.col("cf.mu")[0], 5).alias("mu0"), F.round(F.col("cf.mu")[1], 5).alias("mu1"), F.round("cf.sse", 3).alias("sse"))
SQL["cluster_cfs"] = _PER + "SELECT cluster, round(n, 5) AS n, round(m0, 5) AS mu0, round(m1, 5) AS mu1, round(sse, 3) AS sse FROM s"
QUERIES["rmsd_hier_ward"] = lambda spark, sf: quality.rmsd(_clusters(spark, sf)).select(F.round("rmsd", 5).alias("rmsd"), "k")
SQL["rmsd_hier_ward"] = _PER + "SELECT round(sqrt(sum(sse) / sum(n)), 5) AS rmsd, count(*) AS k FROM s"


def rmsd_cf_vs_points(spark, sf) -> DataFrame:
    """RMSD of five clusters of nations from features, and from the customers themselves."""
    cut = hier.cut_k(ward(spark, sf), 5)
    c = T(spark, sf, "customer").select(F.col("c_custkey").alias("id"), F.col("c_nationkey").cast("long").alias("cf_id"), F.array(F.col("c_acctbal") / 1000, F.col("c_custkey") / 1000).alias("vec"))
    points = quality.rmsd_from_points(c.select("id", "vec"), hier.label_points(c.select("id", "cf_id"), cut), 2)
    return quality.rmsd(hier.cluster_cfs(items(spark, sf), cut, 2)).select(F.round("rmsd", 5).alias("by_features")).crossJoin(points.select(F.round("rmsd", 5).alias("by_points")))


QUERIES["rmsd_cf_vs_points"] = rmsd_cf_vs_points
SQL["rmsd_cf_vs_points"] = _PER + """, p AS (SELECT cluster, c_acctbal / 1000 AS x, c_custkey / 1000.0 AS y FROM customer JOIN labels ON c_nationkey = item),
q AS (SELECT count(*) * (var_pop(x) + var_pop(y)) AS sse, count(*) AS n FROM p GROUP BY cluster)
SELECT (SELECT round(sqrt(sum(sse) / sum(n)), 5) FROM s) AS by_features, (SELECT round(sqrt(sum(sse) / sum(n)), 5) FROM q) AS by_points"""


def w6_nations(spark, sf) -> DataFrame:
    """No compression below the cap: RMSD at five clusters of the nations' centres, on them and through a tree."""
    p = items(spark, sf).select(F.col("cf_id").alias("id"), F.col("mu").alias("vec"), F.lit(1.0).alias("w"))
    found = None
    for mode in ("full", "cf_linkage"):
        it, merges = pl.cluster(p, 2, mode, "cached", "ward", max_leaves=1000)
        row = quality.rmsd(hier.cluster_cfs(it, hier.cut_k(merges, 5), 2)).select(F.lit(mode).alias("mode"), F.round("rmsd", 5).alias("rmsd"))
        found = row if found is None else found.unionByName(row)
    return found


QUERIES["w6_nations"] = w6_nations
SQL["w6_nations"] = _PER.replace(NATION2, _ONES) + "SELECT unnest(['full', 'cf_linkage']) AS mode, round(sqrt(sum(sse) / sum(n)), 5) AS rmsd FROM s"
QUERIES["sweep_k"] = lambda spark, sf: hier.sweep_k(ward(spark, sf), [1, 2, 5, 10, 25]).groupBy("k").agg(F.countDistinct("cluster").alias("clusters"), F.count("*").alias("items"))
SQL["sweep_k"] = "SELECT CAST(k AS INTEGER) AS k, CAST(k AS BIGINT) AS clusters, CAST(25 AS BIGINT) AS items FROM (VALUES (1), (2), (5), (10), (25)) AS v(k)"
QUERIES["merge_overlap"] = lambda spark, sf: hier.merge_overlap(ward(spark, sf), tree(spark, sf, "cf_linkage", "scan", "ward"))
SQL["merge_overlap"] = f"SELECT CAST({M - 1} AS BIGINT) AS shared"


def height_gaps(spark, sf) -> DataFrame:
    from pyspark.sql import Window

    w = Window.orderBy("step")  # a merge table is bounded by the tree's cap
    m = ward(spark, sf)
    return m.select(F.col("step").cast("long").alias("step"), F.round(F.col("height") - F.lag("height").over(w), 5).alias("gap"))


QUERIES["height_gaps"] = height_gaps
SQL["height_gaps"] = WARD + "SELECT CAST(step AS BIGINT) AS step, round(height - lag(height) OVER (ORDER BY step), 5) AS gap FROM merges"


def label_points(spark, sf) -> DataFrame:
    c = T(spark, sf, "customer").select(F.col("c_custkey").alias("id"), F.col("c_nationkey").cast("long").alias("cf_id"))
    return hier.label_points(c, hier.cut_k(ward(spark, sf), 5))


QUERIES["label_points"], SQL["label_points"] = label_points, _CUT + "SELECT c_custkey AS id, cluster FROM customer JOIN labels ON c_nationkey = item"
