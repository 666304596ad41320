"""Features, distances and linkages on the given tables, each with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aggclust.functions import cfdist, features as ft, linkage as link
from aggclust.sources import points as src

T = src.table
QUERIES: dict = {}
SQL: dict[str, str] = {}
L5 = list(src.LINE5)
LINE5_SQL = "CAST(l_quantity AS DOUBLE) AS q, l_extendedprice / 2085 AS p, l_discount * 500 AS d, l_tax * 625 AS t, date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) / 50.0 AS s"


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return keep


def flat(df: DataFrame, cf: str, d: int, *keep) -> DataFrame:
    """Feature columns, rounded as engines sum in different orders."""
    c = F.col(cf)
    return df.select(*keep, F.round(c["n"], 6).alias("n"), *(F.round(c["mu"][i], 6).alias(f"mu{i}") for i in range(d)), F.round(c["sse"], 3).alias("sse"))


# ---- features

@query("cf_point", "SELECT p_partkey, CAST(1 AS DOUBLE) AS n, CAST(p_size AS DOUBLE) AS mu0, p_retailprice AS mu1, CAST(0 AS DOUBLE) AS sse FROM part")
def cf_point(spark: SparkSession, sf: str) -> DataFrame:
    v = T(spark, sf, "part").select("p_partkey", ft.cf_point(F.array(F.col("p_size").cast("double"), "p_retailprice")).alias("c"))
    return v.select("p_partkey", "c.n", F.col("c.mu")[0].alias("mu0"), F.col("c.mu")[1].alias("mu1"), "c.sse")


@query("cf_weighted", "SELECT l_quantity AS n, l_discount AS mu0, l_tax AS mu1, CAST(0 AS DOUBLE) AS sse FROM lineitem")
def cf_weighted(spark, sf):
    v = T(spark, sf, "lineitem").select(ft.cf_point(F.array("l_discount", "l_tax"), "l_quantity").alias("c"))
    return v.select(F.col("c.n").alias("n"), F.col("c.mu")[0].alias("mu0"), F.col("c.mu")[1].alias("mu1"), "c.sse")


NATION2 = "SELECT c_nationkey AS k, count(*)::DOUBLE AS n, avg(c_acctbal / 1000) AS m0, avg(c_custkey / 1000.0) AS m1, count(*) * (var_pop(c_acctbal / 1000) + var_pop(c_custkey / 1000.0)) AS sse FROM customer GROUP BY c_nationkey"
SUPPLIER2 = "SELECT s_nationkey AS k, count(*)::DOUBLE AS n, avg(s_acctbal / 1000) AS m0, avg(s_suppkey / 1000.0) AS m1, count(*) * (var_pop(s_acctbal / 1000) + var_pop(s_suppkey / 1000.0)) AS sse FROM supplier GROUP BY s_nationkey"
PAIR_SQL = f"WITH a AS ({NATION2}), b AS ({SUPPLIER2}), pr AS (SELECT a.k, a.n na, a.m0 a0, a.m1 a1, a.sse sa, b.n nb, b.m0 b0, b.m1 b1, b.sse sb FROM a JOIN b ON a.k = b.k), e AS (SELECT *, (a0-b0)*(a0-b0)+(a1-b1)*(a1-b1) AS g, na+nb AS nn, sa+sb+na*nb/(na+nb)*((a0-b0)*(a0-b0)+(a1-b1)*(a1-b1)) AS su FROM pr)"
FORMS_SQL = {"D0": "sqrt(g)", "D1": "abs(a0-b0)+abs(a1-b1)", "D2": "sqrt(sa/na+sb/nb+g)", "D3": "CASE WHEN nn > 1 THEN sqrt(2*su/(nn-1)) ELSE 0 END", "D4": "sqrt(na*nb/nn*g)", "R": "sqrt(su/nn)"}


def nation_cf2(spark, sf) -> DataFrame:
    """k and the two-dimensional feature of each nation's customers."""
    c = T(spark, sf, "customer").select(F.col("c_nationkey").alias("k"), (F.col("c_acctbal") / 1000).alias("x"), (F.col("c_custkey") / 1000).alias("y"))
    return ft.cf_agg(c, ["k"], ["x", "y"])


def nation_pair(spark, sf) -> DataFrame:
    s = T(spark, sf, "supplier").select(F.col("s_nationkey").alias("k"), (F.col("s_acctbal") / 1000).alias("x"), (F.col("s_suppkey") / 1000).alias("y"))
    return nation_cf2(spark, sf).withColumnRenamed("cf", "a").join(ft.cf_agg(s, ["k"], ["x", "y"], "b"), "k")


def _flat_sql(src_sql: str) -> str:
    return f"SELECT k, round(n, 6) AS n, round(m0, 6) AS mu0, round(m1, 6) AS mu1, round(sse, 3) AS sse FROM ({src_sql})"


@query("cf_merge_pair", f"{PAIR_SQL} SELECT k, round(nn, 6) AS n, round((na*a0+nb*b0)/nn, 6) AS mu0, round((na*a1+nb*b1)/nn, 6) AS mu1, round(su, 3) AS sse FROM e")
def cf_merge_pair(spark, sf):
    return flat(nation_pair(spark, sf).select("k", ft.cf_merge("a", "b").alias("c")), "c", 2, "k")


@query("cf_by_nation", _flat_sql(NATION2))
def cf_by_nation(spark, sf):
    return flat(nation_cf2(spark, sf), "cf", 2, "k")


_MEANS = ", ".join(f"round(avg({c}), 6) AS mu{i}" for i, c in enumerate(L5))
_SSE = "round(count(*) * (" + " + ".join(f"var_pop({c})" for c in L5) + "), 3) AS sse"


@query("cf_by_flag", f"SELECT l_returnflag, l_linestatus, count(*)::DOUBLE AS n, {_MEANS}, {_SSE} FROM (SELECT l_returnflag, l_linestatus, {LINE5_SQL} FROM lineitem) GROUP BY ALL")
def cf_by_flag(spark, sf):
    v = src.line5(T(spark, sf, "lineitem"), ("l_returnflag", "l_linestatus"))
    return flat(ft.cf_agg(v, ["l_returnflag", "l_linestatus"], L5), "cf", 5, "l_returnflag", "l_linestatus")


@query("cf_total", f"SELECT count(*)::DOUBLE AS n, {_MEANS}, {_SSE} FROM (SELECT {LINE5_SQL} FROM lineitem)")
def cf_total(spark, sf):
    return flat(ft.cf_agg(src.line5(T(spark, sf, "lineitem")), [], L5), "cf", 5)


_REGION = "SELECT n_regionkey AS k, count(*)::DOUBLE AS n, avg(c_acctbal / 1000) AS m0, avg(c_custkey / 1000.0) AS m1, count(*) * (var_pop(c_acctbal / 1000) + var_pop(c_custkey / 1000.0)) AS sse FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_regionkey"


@query("cf_rollup_region", _flat_sql(_REGION))
def cf_rollup_region(spark, sf):
    """Merged features of the nations equal the features of the regions' own rows."""
    n = T(spark, sf, "nation").select(F.col("n_nationkey").alias("k"), F.col("n_regionkey").alias("r"))
    return flat(ft.cf_merge_agg(nation_cf2(spark, sf).join(n, "k"), ["r"], 2), "cf", 2, F.col("r").alias("k"))


@query("cf_fold_region", _flat_sql(_REGION))
def cf_fold_region(spark, sf):
    n = T(spark, sf, "nation").select(F.col("n_nationkey").alias("k"), F.col("n_regionkey").alias("r"))
    return flat(ft.cf_merge_agg(nation_cf2(spark, sf).join(n, "k"), ["r"], 2, strategy="fold"), "cf", 2, F.col("r").alias("k"))


_LEVELS = "SELECT n_regionkey, n_nationkey, count(*)::DOUBLE AS n, round(avg(c_acctbal), 6) AS mu0, round(count(*) * var_pop(c_acctbal), 2) AS sse FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY "


def _levels(spark, sf, how: str) -> DataFrame:
    j = T(spark, sf, "customer").join(F.broadcast(T(spark, sf, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    n = F.count("*").cast("double")
    aggs = (n.alias("n"), F.round(F.avg("c_acctbal"), 6).alias("mu0"), F.round(n * F.var_pop("c_acctbal"), 2).alias("sse"))
    if how == "sets":
        return j.groupingSets([["n_regionkey"], ["n_nationkey"]], "n_regionkey", "n_nationkey").agg(*aggs)
    return getattr(j, how)("n_regionkey", "n_nationkey").agg(*aggs)


query("cf_rollup", _LEVELS + "ROLLUP (n_regionkey, n_nationkey)")(lambda spark, sf: _levels(spark, sf, "rollup"))
query("cf_hierarchy", _LEVELS + "ROLLUP (n_regionkey, n_nationkey)")(lambda spark, sf: _levels(spark, sf, "rollup"))
query("cf_cube", _LEVELS + "CUBE (n_regionkey, n_nationkey)")(lambda spark, sf: _levels(spark, sf, "cube"))
query("cf_grouping_sets", _LEVELS + "GROUPING SETS ((n_regionkey), (n_nationkey))")(lambda spark, sf: _levels(spark, sf, "sets"))


@query("naive_by_flag", "SELECT l_returnflag, count(*)::DOUBLE AS n, round(sum(q), 2) AS ls0, round(sum(p), 2) AS ls1, round(sum(q*q + p*p), 1) AS ss FROM (SELECT l_returnflag, " + LINE5_SQL + " FROM lineitem) GROUP BY l_returnflag")
def naive_by_flag(spark, sf):
    v = ft.naive_agg(src.line5(T(spark, sf, "lineitem"), ("l_returnflag",)), ["l_returnflag"], ["q", "p"])
    return v.select("l_returnflag", "nf.n", F.round(F.col("nf.ls")[0], 2).alias("ls0"), F.round(F.col("nf.ls")[1], 2).alias("ls1"), F.round("nf.ss", 1).alias("ss"))


@query("naive_sse_by_flag", "SELECT l_returnflag, round(sum(q*q + p*p) - (sum(q)*sum(q) + sum(p)*sum(p)) / count(*), 1) AS sse FROM (SELECT l_returnflag, " + LINE5_SQL + " FROM lineitem) GROUP BY l_returnflag")
def naive_sse_by_flag(spark, sf):
    v = ft.naive_agg(src.line5(T(spark, sf, "lineitem"), ("l_returnflag",)), ["l_returnflag"], ["q", "p"])
    return v.select("l_returnflag", F.round(ft.naive_sse("nf"), 1).alias("sse"))


@query("stability_gap", "SELECT true AS stable_holds, true AS naive_fails")
def stability_gap(spark, sf):
    """At a shift of 1e8 the stable feature keeps its value and the older one loses it."""
    g = ft.stability_gap(src.line5(T(spark, sf, "lineitem")), ["q", "p", "d", "t"], 1e8)
    true = F.max(F.when(F.col("shift") == 0, F.col("stable_sse")))
    far = lambda c: F.max(F.when(F.col("shift") > 0, F.abs(F.col(c))))
    return g.agg((F.abs(far("stable_sse") / true - 1) < 1e-6).alias("stable_holds"), (F.abs(far("naive_sse") / true - 1) > 1e-3).alias("naive_fails"))


@query("cf_readouts", f"SELECT k, round(m0, 6) AS c0, round(sse / n, 6) AS variance, round(sqrt(sse / n), 6) AS radius, round(CASE WHEN n > 1 THEN sqrt(2 * sse / (n - 1)) ELSE 0 END, 6) AS diameter FROM ({NATION2})")
def cf_readouts(spark, sf):
    c = nation_cf2(spark, sf)
    return c.select("k", F.round(ft.cf_center("cf")[0], 6).alias("c0"), F.round(ft.cf_variance("cf"), 6).alias("variance"), F.round(ft.cf_radius("cf"), 6).alias("radius"), F.round(ft.cf_diameter("cf"), 6).alias("diameter"))


@query("cf_subtract", _flat_sql("SELECT c_nationkey AS k, count(*)::DOUBLE AS n, avg(c_acctbal / 1000) AS m0, avg(c_custkey / 1000.0) AS m1, count(*) * (var_pop(c_acctbal / 1000) + var_pop(c_custkey / 1000.0)) AS sse FROM customer WHERE c_custkey % 3 <> 0 GROUP BY c_nationkey"))
def cf_subtract(spark, sf):
    c = T(spark, sf, "customer").select(F.col("c_nationkey").alias("k"), (F.col("c_acctbal") / 1000).alias("x"), (F.col("c_custkey") / 1000).alias("y"), "c_custkey")
    part = ft.cf_agg(c.where("c_custkey % 3 = 0"), ["k"], ["x", "y"], "part")
    both = ft.cf_agg(c, ["k"], ["x", "y"], "whole").join(part, "k", "left")
    rest = F.when(F.col("part").isNull(), F.col("whole")).otherwise(ft.cf_subtract("whole", "part"))
    return flat(both.select("k", rest.alias("c")).where("c IS NOT NULL"), "c", 2, "k")


# ---- distances

for _k in cfdist.KINDS:
    query(f"dist_{_k.lower()}", f"{PAIR_SQL} SELECT k, round({FORMS_SQL[_k]}, 6) AS d FROM e")(
        lambda spark, sf, k=_k: nation_pair(spark, sf).select("k", F.round(cfdist.cf_distance("a", "b", k), 6).alias("d"))
    )
_ALL = ", ".join(f"round({FORMS_SQL[k]}, 6) AS {k.lower()}" for k in cfdist.KINDS)


@query("dist_profile", f"{PAIR_SQL} SELECT k, {_ALL} FROM e")
def dist_profile(spark, sf):
    p = cfdist.distance_profile(nation_pair(spark, sf), keep=("k",))
    return p.select("k", *(F.round(k.lower(), 6).alias(k.lower()) for k in cfdist.KINDS))


@query("dist_self", f"SELECT k, CAST(0 AS DOUBLE) AS d0, round(sqrt(2 * sse / n), 6) AS d2, round(CASE WHEN 2 * n > 1 THEN sqrt(4 * sse / (2 * n - 1)) ELSE 0 END, 6) AS d3, CAST(0 AS DOUBLE) AS d4, round(sqrt(sse / n), 6) AS r FROM ({NATION2})")
def dist_self(spark, sf):
    """A feature to itself: D2, D3 and R are not zero, so they are no metrics."""
    p = cfdist.distance_profile(nation_cf2(spark, sf).select("k", F.col("cf").alias("a"), F.col("cf").alias("b")), keep=("k",))
    return p.select("k", *(F.round(c, 6).alias(c) for c in ("d0", "d2", "d3", "d4", "r")))


_MEMBERS = "SELECT c_nationkey AS k, 'a' AS w, c_acctbal / 1000 AS x, c_custkey / 1000.0 AS y FROM customer UNION ALL SELECT s_nationkey, 'b', s_acctbal / 1000, s_suppkey / 1000.0 FROM supplier"
_BOTH = f"WITH m AS (SELECT * FROM ({_MEMBERS}) WHERE k IN (SELECT s_nationkey FROM supplier) AND k IN (SELECT c_nationkey FROM customer))"
_CROSS = "(u.x - v.x) * (u.x - v.x) + (u.y - v.y) * (u.y - v.y)"
_BRUTE = {
    "D2": f"SELECT u.k, round(sqrt(avg({_CROSS})), 6) AS d FROM m u JOIN m v ON u.k = v.k AND u.w = 'a' AND v.w = 'b' GROUP BY u.k",
    "D3": f"SELECT u.k, round(sqrt(sum({_CROSS}) / (max(c) * (max(c) - 1))), 6) AS d FROM m u JOIN m v ON u.k = v.k JOIN (SELECT k, count(*) AS c FROM m GROUP BY k) z ON z.k = u.k GROUP BY u.k",
    "D4": "SELECT k, round(sqrt(greatest(0, all_sse - own)), 6) AS d FROM (SELECT k, count(*) * (var_pop(x) + var_pop(y)) AS all_sse FROM m GROUP BY k) JOIN (SELECT k, sum(s) AS own FROM (SELECT k, w, count(*) * (var_pop(x) + var_pop(y)) AS s FROM m GROUP BY k, w) GROUP BY k) USING (k)",
    "R": "SELECT k, round(sqrt(var_pop(x) + var_pop(y)), 6) AS d FROM m GROUP BY k",
}
for _k, _s in _BRUTE.items():
    query(f"dist_{_k.lower()}_brute", f"{_BOTH} {_s}")(lambda spark, sf, k=_k: nation_pair(spark, sf).select("k", F.round(cfdist.cf_distance("a", "b", k), 6).alias("d")))


# ---- linkages

_GROUP = "SELECT c_custkey % 6 AS g, c_acctbal / 1000 AS x, c_custkey / 1000.0 AS y FROM customer"


def groups(spark, sf) -> DataFrame:
    return T(spark, sf, "customer").select((F.col("c_custkey") % 6).alias("g"), F.array(F.col("c_acctbal") / 1000, F.col("c_custkey") / 1000).alias("vec"))


_BETWEEN = {
    "single": f"min(sqrt({_CROSS}))", "complete": f"max(sqrt({_CROSS}))", "upgma": f"avg(sqrt({_CROSS}))", "upgma_sq": f"avg({_CROSS})",
    "upgmc": "pow(avg(u.x) - avg(v.x), 2) + pow(avg(u.y) - avg(v.y), 2)",
    "ward": "2.0 * (count(DISTINCT u.y) * count(DISTINCT v.y)) / (count(DISTINCT u.y) + count(DISTINCT v.y)) * (pow(avg(u.x) - avg(v.x), 2) + pow(avg(u.y) - avg(v.y), 2))",
}
for _n, _s in _BETWEEN.items():
    query(f"link_{_n}", f"WITH m AS ({_GROUP}) SELECT u.g AS a, v.g AS b, round({_s}, 6) AS d FROM m u JOIN m v ON u.g < v.g GROUP BY u.g, v.g")(
        lambda spark, sf, n=_n: link.linkage_between(groups(spark, sf), "g", "vec", n.removesuffix("_sq"), n.endswith("_sq")).select("a", "b", F.round("d", 6).alias("d"))
    )

# One step of the recurrence on random triples, against the definitions where there is one.
_TRIPLE = "SELECT s_suppkey AS id, 1.0 + s_suppkey % 7 AS na, 1.0 + s_suppkey % 5 AS nb, 1.0 + s_suppkey % 3 AS nc, abs(s_acctbal) / 997 + 1 AS dac, abs(s_acctbal) / 1511 + 2 AS dbc, abs(s_acctbal) / 3001 + 0.5 AS dab FROM supplier"
_RECUR = {
    "single": "least(dac, dbc)", "complete": "greatest(dac, dbc)", "upgma": "(na * dac + nb * dbc) / (na + nb)", "wpgma": "(dac + dbc) / 2",
    "upgmc": "(na * dac + nb * dbc) / (na + nb) - na * nb * dab / ((na + nb) * (na + nb))", "wpgmc": "(dac + dbc) / 2 - dab / 4",
    "ward": "((na + nc) * dac + (nb + nc) * dbc - nc * dab) / (na + nb + nc)",
}


def triples(spark, sf) -> DataFrame:
    b = F.abs("s_acctbal")
    k = F.col("s_suppkey")
    return T(spark, sf, "supplier").select(k.alias("id"), (1.0 + k % 7).alias("na"), (1.0 + k % 5).alias("nb"), (1.0 + k % 3).alias("nc"), (b / 997 + 1).alias("dac"), (b / 1511 + 2).alias("dbc"), (b / 3001 + 0.5).alias("dab"))


def _recur(spark, sf, name: str) -> DataFrame:
    c = F.col
    return triples(spark, sf).select("id", F.round(link.recur(name, c("dac"), c("dbc"), c("dab"), c("na"), c("nb"), c("nc")), 6).alias("d"))


for _n, _s in _RECUR.items():
    query(f"recur_{_n}", f"SELECT CAST(id AS BIGINT) AS id, round({_s}, 6) AS d FROM ({_TRIPLE})")(lambda spark, sf, n=_n: _recur(spark, sf, n))


@query("tab2_identities", f"{PAIR_SQL} SELECT k, round(sa/na + sb/nb + g, 5) AS upgma, round(g, 5) AS upgmc, round(2*na*nb/nn*g, 5) AS ward FROM e")
def tab2_identities(spark, sf):
    """The squared distances of features that equal linkages."""
    d = lambda kind: cfdist.cf_distance("a", "b", kind, squared=True)
    return nation_pair(spark, sf).select("k", F.round(d("D2"), 5).alias("upgma"), F.round(d("D0"), 5).alias("upgmc"), F.round(2 * d("D4"), 5).alias("ward"))


@query("weighted_equiv", "SELECT CAST(id AS BIGINT) AS id, true AS mean_same, true AS centre_same FROM (" + _TRIPLE + ")")
def weighted_equiv(spark, sf):
    """The weighted linkages are the unweighted ones with all sizes one."""
    c, one = F.col, F.lit(1.0)
    r = lambda n, *s: link.recur(n, c("dac"), c("dbc"), c("dab"), *s)
    same = lambda a, b: F.abs(r(a, one, one, c("nc")) - r(b, c("na"), c("nb"), c("nc"))) < 1e-12
    return triples(spark, sf).select("id", same("upgma", "wpgma").alias("mean_same"), same("upgmc", "wpgmc").alias("centre_same"))


# Every supplier's lines by return flag, A, N and R: three clusters, with their sizes and means.
_FLAGS = {"a": "A", "b": "N", "c": "R"}
_FLAG_SQL = (
    "f AS (SELECT l_suppkey AS k, " + ", ".join(f"CAST(count(*) FILTER (l_returnflag = '{v}') AS DOUBLE) AS n{c}, avg(l_quantity) FILTER (l_returnflag = '{v}') AS x{c}, avg(l_extendedprice / 2085) FILTER (l_returnflag = '{v}') AS y{c}" for c, v in _FLAGS.items())
    + " FROM lineitem GROUP BY l_suppkey), t AS (SELECT *, " + ", ".join(f"pow(x{u} - x{v}, 2) + pow(y{u} - y{v}, 2) AS {u}{v}" for u, v in ("ab", "ac", "bc")) + " FROM f WHERE na > 0 AND nb > 0 AND nc > 0)"
)


def flag_clusters(spark, sf) -> DataFrame:
    """k, sizes na, nb, nc, and squared distances ab, ac, bc of the means; suppliers without lines of a flag have no three clusters."""
    of = lambda v, c: F.when(F.col("l_returnflag") == v, c)
    parts = []
    for c, v in _FLAGS.items():
        parts += [F.count(of(v, 1)).cast("double").alias(f"n{c}"), F.avg(of(v, F.col("l_quantity"))).alias(f"x{c}"), F.avg(of(v, F.col("l_extendedprice") / 2085)).alias(f"y{c}")]
    f = T(spark, sf, "lineitem").groupBy(F.col("l_suppkey").alias("k")).agg(*parts).where("na > 0 AND nb > 0 AND nc > 0")
    sq = lambda u, v: F.pow(F.col(f"x{u}") - F.col(f"x{v}"), 2) + F.pow(F.col(f"y{u}") - F.col(f"y{v}"), 2)
    return f.select("k", "na", "nb", "nc", *(sq(u, v).alias(u + v) for u, v in ("ab", "ac", "bc")))


_COEFFICIENTS = {
    "single": "0.5, 0.5, 0.0, -0.5", "complete": "0.5, 0.5, 0.0, 0.5", "upgma": "na / (na + nb), nb / (na + nb), 0.0, 0.0", "wpgma": "0.5, 0.5, 0.0, 0.0",
    "upgmc": "na / (na + nb), nb / (na + nb), -na * nb / ((na + nb) * (na + nb)), 0.0", "wpgmc": "0.5, 0.5, -0.25, 0.0",
    "ward": "(na + nc) / (na + nb + nc), (nb + nc) / (na + nb + nc), -nc / (na + nb + nc), 0.0",
}
_COEFFICIENT_ROWS = " UNION ALL ".join("SELECT k, '{}' AS linkage, {}::DOUBLE AS alpha_a, {}::DOUBLE AS alpha_b, {}::DOUBLE AS beta, {}::DOUBLE AS gamma FROM t".format(n, *(f"({x})" for x in v.split(", "))) for n, v in _COEFFICIENTS.items())


@query("coefficients", f"WITH {_FLAG_SQL} SELECT k, linkage, round(alpha_a, 6) AS alpha_a, round(alpha_b, 6) AS alpha_b, round(beta, 6) AS beta, round(gamma, 6) AS gamma FROM ({_COEFFICIENT_ROWS})")
def coefficients(spark, sf):
    """The coefficients of every linkage for the sizes of each supplier's three clusters."""
    c = link.coefficient_table(flag_clusters(spark, sf), "k")
    return c.select("k", "linkage", *(F.round(x, 6).alias(x) for x in ("alpha_a", "alpha_b", "beta", "gamma")))


@query("wpgma_history", f"WITH {_FLAG_SQL} " + " UNION ALL ".join(f"SELECT k, '{u}' AS first, round((sqrt({x}) + sqrt({y})) / 2, 6) AS d FROM t" for u, x, y in (("ab", "ac", "bc"), ("ac", "ab", "bc"), ("bc", "ab", "ac"))))
def wpgma_history(spark, sf):
    """Three objects for each supplier, the means of its clusters: the last height depends on which pair went first."""
    # The distances of the object left over to the two that merged first.
    last = lambda x, y: F.round(link.recur("wpgma", F.sqrt(x), F.sqrt(y), F.lit(0.0)), 6)
    rows = F.array(*(F.struct(F.lit(u).alias("first"), last(x, y).alias("d")) for u, x, y in (("ab", "ac", "bc"), ("ac", "ab", "bc"), ("bc", "ab", "ac"))))
    return flag_clusters(spark, sf).select("k", F.inline(rows))


@query("inversion_demo", f"WITH {_FLAG_SQL}, o AS (SELECT k, list_sort([ab, ac, bc]) AS d FROM t), h AS (SELECT k, d[1] AS first, d[2] AS before, (d[2] + d[3]) / 2 - d[1] / 4 AS after FROM o) SELECT k, round(first, 6) AS first, round(before, 6) AS before, round(after, 6) AS after, after < before AS inverted FROM h")
def inversion_demo(spark, sf):
    """The nearest two of each supplier's three means merge: whether the pair's centre is nearer to the third than either was."""
    d = F.array_sort(F.array("ab", "ac", "bc"))
    one = F.lit(1.0)
    p = flag_clusters(spark, sf).select("k", d[0].alias("first"), d[1].alias("before"), d[2].alias("_far"))
    p = p.withColumn("after", link.recur("upgmc", F.col("before"), F.col("_far"), F.col("first"), one, one, one))
    return p.select("k", *(F.round(c, 6).alias(c) for c in ("first", "before", "after")), (F.col("after") < F.col("before")).alias("inverted"))
