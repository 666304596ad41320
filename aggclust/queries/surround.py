"""Sources, joins, aggregates, windows and functions around the clustering operators."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from aggclust.functions import cfdist, features as ft
from aggclust.operators import blocks, quality, rounds
from aggclust.queries.basics import L5, LINE5_SQL, NATION2, T, flat, nation_cf2
from aggclust.sources import points as src
from aggclust.sources import storage

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return keep


@query("scan_lineitem", "SELECT l_orderkey, l_quantity, l_discount FROM lineitem WHERE l_quantity > 45 AND l_discount < 0.03")
def scan_lineitem(spark, sf):
    return T(spark, sf, "lineitem").where("l_quantity > 45 AND l_discount < 0.03").select("l_orderkey", "l_quantity", "l_discount")


@query("filter_ship_year", "SELECT l_returnflag, count(*) AS n FROM lineitem WHERE l_shipdate >= TIMESTAMP '1997-01-01' AND l_shipdate < TIMESTAMP '1998-01-01' GROUP BY l_returnflag")
def filter_ship_year(spark, sf):
    v = T(spark, sf, "lineitem").where("l_shipdate >= TIMESTAMP'1997-01-01' AND l_shipdate < TIMESTAMP'1998-01-01'")
    return v.groupBy("l_returnflag").agg(F.count("*").alias("n"))


_R = ", ".join(f"round({c}, 6) AS {c}" for c in L5)


@query("feature_line5", f"SELECT {_R} FROM (SELECT {LINE5_SQL} FROM lineitem)")
def feature_line5(spark, sf):
    return src.line5(T(spark, sf, "lineitem")).select(*(F.round(c, 6).alias(c) for c in L5))


@query("zscore_line5", f"SELECT round(avg(z), 4) + 0.0 AS mean, round(max(z), 5) AS top, round(min(z), 5) AS low FROM (SELECT (q - avg(q) OVER ()) / stddev_pop(q) OVER () AS z FROM (SELECT {LINE5_SQL} FROM lineitem))")
def zscore_line5(spark, sf):
    v = src.line5(T(spark, sf, "lineitem")).select("q")
    m = v.agg(F.avg("q").alias("m"), F.stddev_pop("q").alias("s"))
    z = v.crossJoin(F.broadcast(m)).select(((F.col("q") - F.col("m")) / F.col("s")).alias("z"))
    return z.agg((F.round(F.avg("z"), 4) + 0.0).alias("mean"), F.round(F.max("z"), 5).alias("top"), F.round(F.min("z"), 5).alias("low"))


def _u_sql(b: str, k: int) -> str:
    p = src.PRIME
    t = f"(({b} + {k * src.STEP}) % {p})"
    v = f"(({t} * {t} % {p} + {src.TURN * k} + {b} * {2 * k + 1}) % {p})"
    return f"(({v} * {v} % {p}) / {float(p)})"


_W = src.ROW_WEIGHTS
_HASH = f"SELECT *, (CAST(round(l_extendedprice * 100) AS BIGINT) * {_W[5]} + l_orderkey * {_W[0]} + l_partkey * {_W[1]} + l_suppkey * {_W[2]} + CAST(l_linenumber AS BIGINT) * {_W[3]} + CAST(l_quantity AS BIGINT) * {_W[4]}) % {src.PRIME} AS b FROM lineitem"
CUBE_SQL = f"SELECT {', '.join(f'{_u_sql('b', k + 1)} * 100 AS u{k + 1}' for k in range(5))}, l_partkey FROM ({_HASH})"


@query("feature_cube5", f"SELECT count(*) AS n, {', '.join(f'round(avg(u{k}), 4) AS m{k}, round(var_pop(u{k}), 3) AS v{k}' for k in range(1, 6))} FROM ({CUBE_SQL})")
def feature_cube5(spark, sf):
    v = src.cube5(T(spark, sf, "lineitem"))
    return v.agg(F.count("*").alias("n"), *(x for k in range(1, 6) for x in (F.round(F.avg(f"u{k}"), 4).alias(f"m{k}"), F.round(F.var_pop(f"u{k}"), 3).alias(f"v{k}"))))


def _mix_sql() -> str:
    u = [_u_sql("b", k + 1) for k in range(6)]
    normal = []
    for i in range(0, 6, 2):
        r = f"sqrt(-2 * ln({u[i]} + 1e-9) + 1e-8)"
        normal += [f"{r} * cos(2 * 3.141592653589793 * {u[i + 1]})", f"{r} * sin(2 * 3.141592653589793 * {u[i + 1]})"]
    cols = ", ".join(f"{_u_sql('c', k + 1)} * 100 + 3.0 * {normal[k]} AS g{k + 1}" for k in range(5))
    return f"SELECT comp, {cols} FROM (SELECT *, ((comp * 48271 + 11) % {src.PRIME}) * 16807 % {src.PRIME} AS c FROM (SELECT *, l_partkey % 500 AS comp FROM ({_HASH})))"


MIX_SQL = _mix_sql()


@query("feature_mix5", f"SELECT count(*) AS n, count(DISTINCT comp) AS components, {', '.join(f'round(avg(g{k}), 3) AS m{k}, round(var_pop(g{k}), 2) AS v{k}' for k in range(1, 6))} FROM ({MIX_SQL})")
def feature_mix5(spark, sf):
    v = src.mix5(T(spark, sf, "lineitem"))
    return v.agg(F.count("*").alias("n"), F.countDistinct("comp").alias("components"), *(x for k in range(1, 6) for x in (F.round(F.avg(f"g{k}"), 3).alias(f"m{k}"), F.round(F.var_pop(f"g{k}"), 2).alias(f"v{k}"))))


@query("cf_by_component", f"SELECT comp, count(*)::DOUBLE AS n, round(avg(g1), 4) AS mu0, round(count(*) * (var_pop(g1) + var_pop(g2)), 2) AS sse FROM ({MIX_SQL}) GROUP BY comp")
def cf_by_component(spark, sf):
    c = ft.cf_agg(src.mix5(T(spark, sf, "lineitem")), ["comp"], ["g1", "g2"])
    return c.select("comp", "cf.n", F.round(F.col("cf.mu")[0], 4).alias("mu0"), F.round("cf.sse", 2).alias("sse"))


@query("prefix_rows", f"SELECT l_orderkey, l_partkey, b FROM ({_HASH}) ORDER BY b, l_orderkey, l_partkey LIMIT 500")
def prefix_rows(spark, sf):
    """The first rows in hash order: a reproducible sample."""
    return T(spark, sf, "lineitem").select("l_orderkey", "l_partkey", src.row_hash().alias("b")).orderBy("b", "l_orderkey", "l_partkey").limit(500)


@query("join_labels", "SELECT quality, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents JOIN labels USING (doc_id) GROUP BY quality")
def join_labels(spark, sf):
    return T(spark, sf, "documents").join(T(spark, sf, "labels"), "doc_id").groupBy("quality").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("docs_unlabelled", "SELECT doc_id FROM documents ANTI JOIN labels USING (doc_id)")
def docs_unlabelled(spark, sf):
    return T(spark, sf, "documents").select("doc_id").join(T(spark, sf, "labels"), "doc_id", "left_anti")


@query("docs_labelled", "SELECT doc_id FROM documents SEMI JOIN labels USING (doc_id)")
def docs_labelled(spark, sf):
    return T(spark, sf, "documents").select("doc_id").join(T(spark, sf, "labels"), "doc_id", "left_semi")


@query("join_orders_customer", "SELECT c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def join_orders_customer(spark, sf):
    o, c = T(spark, sf, "orders"), T(spark, sf, "customer")
    return o.join(c.hint("merge"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


_EMB = "WITH e AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings)"
_PAIR = "list_sum(list_transform(list_zip(a.v, b.v), lambda z: (z[1] - z[2]) * (z[1] - z[2])))"


def _embeddings(spark, sf) -> DataFrame:
    return T(spark, sf, "embeddings").select("vec_id", "embedding")


@query("pairwise_embeddings", f"{_EMB} SELECT count(*) AS pairs, round(min(d), 5) AS low, round(avg(d), 5) AS mean FROM (SELECT sqrt({_PAIR}) AS d FROM e a JOIN e b ON a.vec_id < b.vec_id)")
def pairwise_embeddings(spark, sf):
    return blocks.spread(_embeddings(spark, sf), "vec_id", "embedding").select("pairs", F.round("low", 5).alias("low"), F.round("mean", 5).alias("mean"))


@query("closest_pairs", f"{_EMB} SELECT a.vec_id AS i, b.vec_id AS j, round(sqrt({_PAIR}), 5) AS d FROM e a JOIN e b ON a.vec_id < b.vec_id ORDER BY sqrt({_PAIR}), 1, 2 LIMIT 20")
def closest_pairs(spark, sf):
    return blocks.closest(_embeddings(spark, sf), "vec_id", "embedding", 20).select("i", "j", F.round("d", 5).alias("d"))


@query("nearest_neighbour", f"{_EMB} SELECT a.vec_id AS u, arg_min(b.vec_id, {_PAIR}) AS v, round(sqrt(min({_PAIR})), 5) AS d FROM e a JOIN e b ON a.vec_id <> b.vec_id GROUP BY a.vec_id")
def nearest_neighbour(spark, sf):
    return blocks.nearest(_embeddings(spark, sf), "vec_id", "embedding", 1).select("u", "v", F.round("d", 5).alias("d"))


@query("knn_rank", f"{_EMB} SELECT i, j, rank FROM (SELECT a.vec_id AS i, b.vec_id AS j, CAST(row_number() OVER (PARTITION BY a.vec_id ORDER BY {_PAIR}, b.vec_id) AS INTEGER) AS rank FROM e a JOIN e b ON a.vec_id <> b.vec_id) WHERE rank <= 3")
def knn_rank(spark, sf):
    return blocks.nearest(_embeddings(spark, sf), "vec_id", "embedding", 3).select(F.col("u").alias("i"), F.col("v").alias("j"), "rank")


@query("vector_norms", "SELECT vec_id, round(sqrt(list_sum(list_transform(CAST(embedding AS DOUBLE[]), lambda x: x * x))), 6) AS norm, CAST(len(embedding) AS INTEGER) AS d FROM embeddings")
def vector_norms(spark, sf):
    v = F.col("embedding").cast("array<double>")
    return T(spark, sf, "embeddings").select("vec_id", F.round(F.sqrt(ft.square_norm(v)), 6).alias("norm"), F.size(v).alias("d"))


_N2 = f"WITH f AS ({NATION2})"
_GAP = "(u.m0 - v.m0) * (u.m0 - v.m0) + (u.m1 - v.m1) * (u.m1 - v.m1)"


@query("pairs_nation", f"{_N2} SELECT u.k AS i, v.k AS j, round(sqrt({_GAP}), 6) AS d FROM f u JOIN f v ON u.k < v.k")
def pairs_nation(spark, sf):
    n = nation_cf2(spark, sf)
    a, b = n.select(F.col("k").alias("i"), F.col("cf").alias("a")), n.select(F.col("k").alias("j"), F.col("cf").alias("b"))
    return a.join(b, F.col("i") < F.col("j")).select("i", "j", F.round(cfdist.cf_distance("a", "b", "D0"), 6).alias("d"))


@query("argmin_pair", f"{_N2} SELECT u.k AS i, v.k AS j, round(sqrt({_GAP}), 6) AS d FROM f u JOIN f v ON u.k < v.k ORDER BY {_GAP}, 1, 2 LIMIT 1")
def argmin_pair(spark, sf):
    n = nation_cf2(spark, sf)
    a, b = n.select(F.col("k").alias("i"), F.col("cf").alias("a")), n.select(F.col("k").alias("j"), F.col("cf").alias("b"))
    p = a.join(b, F.col("i") < F.col("j")).select("i", "j", cfdist.cf_distance("a", "b", "D0").alias("d"))
    return p.agg(F.min(F.struct("d", "i", "j")).alias("m")).select("m.i", "m.j", F.round("m.d", 6).alias("d"))


@query("pairs_within_eps", "WITH s AS (SELECT s_suppkey AS id, s_acctbal / 1000 AS x, s_nationkey / 1.0 AS y FROM supplier) SELECT a.id AS i, b.id AS j, round(sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y)), 6) AS d FROM s a JOIN s b ON a.id < b.id AND sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y)) <= 1.3")
def pairs_within_eps(spark, sf):
    s = T(spark, sf, "supplier").select(F.col("s_suppkey").alias("id"), F.array(F.col("s_acctbal") / 1000, F.col("s_nationkey").cast("double")).alias("vec"))
    return rounds.pairs_within_eps(s, 2, 1.3).select("i", "j", F.round("d", 6).alias("d"))


_WIN = "SELECT event_id, user_id, ts, value, CAST(floor(epoch(ts)) AS BIGINT) // 3600 AS h FROM events"


@query("asof_event", f"WITH w AS (SELECT h, count(*) AS n, avg(value) AS m FROM ({_WIN}) GROUP BY h) SELECT event_id, (SELECT max(w.h) FROM w WHERE w.h < e.h) AS h, round((SELECT arg_max(w.m, w.h) FROM w WHERE w.h < e.h), 6) AS mean FROM ({_WIN}) e")
def asof_event(spark, sf):
    """Each event with the feature of the last hour before it that has any events."""
    e = T(spark, sf, "events").withColumn("h", F.floor(F.unix_timestamp("ts") / 3600).cast("long"))
    w = ft.cf_agg(e, ["h"], ["value"])
    # Hours in order: one row each, so the window's single partition is bounded by the time span.
    before = Window.orderBy("h")
    w = w.select("h", F.lag("h").over(before).alias("prev"), F.lag(F.col("cf.mu")[0]).over(before).alias("mean"))
    return e.join(w, "h").select("event_id", F.col("prev").alias("h"), F.round("mean", 6).alias("mean"))


@query("interval_events", f"WITH w AS (SELECT g AS lo, g + 86400 * 7 AS hi FROM (SELECT unnest(generate_series((SELECT (min(epoch(ts))::BIGINT // 86400) * 86400 FROM events), (SELECT max(epoch(ts))::BIGINT FROM events), 86400)) AS g)) SELECT lo, count(*) AS n, round(avg(value), 5) AS mean FROM w JOIN events ON epoch(ts) >= lo AND epoch(ts) < hi GROUP BY lo")
def interval_events(spark, sf):
    """Events in every week that begins on a day of the table: each row is sent to its seven windows."""
    e = T(spark, sf, "events").select(F.unix_timestamp("ts").alias("s"), "value")
    day = (F.floor(F.col("s") / 86400) * 86400).cast("long")
    first = e.agg(F.min(day).alias("first"))
    rows = e.crossJoin(F.broadcast(first)).withColumn("lo", F.explode(F.sequence(F.greatest("first", day - 6 * 86400), day, F.lit(86400).cast("long"))))
    return rows.groupBy("lo").agg(F.count("*").alias("n"), F.round(F.avg("value"), 5).alias("mean"))


@query("alive_after_merge", f"{_N2}, b AS (SELECT u.k AS i, v.k AS j FROM f u JOIN f v ON u.k < v.k ORDER BY {_GAP}, 1, 2 LIMIT 1) SELECT k FROM f WHERE k NOT IN (SELECT j FROM b)")
def alive_after_merge(spark, sf):
    gone = argmin_pair(spark, sf).select(F.col("j").alias("k"))
    return nation_cf2(spark, sf).select("k").join(gone, "k", "left_anti")


@query("distinct_vectors", "SELECT count(*) AS n, CAST(sum(c) AS BIGINT) AS total, max(c) AS most FROM (SELECT count(*) AS c FROM lineitem GROUP BY l_quantity, l_discount, l_tax)")
def distinct_vectors(spark, sf):
    v = T(spark, sf, "lineitem").groupBy("l_quantity", "l_discount", "l_tax").agg(F.count("*").alias("c"))
    return v.agg(F.count("*").alias("n"), F.sum("c").alias("total"), F.max("c").alias("most"))


@query("threshold_guess")
def threshold_guess(spark, sf):
    """Approximate spread of each coordinate, from which a first threshold follows."""
    v = src.line5(T(spark, sf, "lineitem"))
    return v.agg(*(F.percentile_approx(c, [0.25, 0.75], 1000).alias(c) for c in L5), F.approx_count_distinct("p").alias("distinct_p")).select(*((F.col(c)[1] - F.col(c)[0]).alias(c) for c in L5), "distinct_p")


@query("running_cf", "SELECT event_id, count(*) OVER w AS n, round(avg(value) OVER w, 6) AS mean, round(var_pop(value * 1.0371) OVER w, 5) AS variance FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)")
def running_cf(spark, sf):
    return _windowed(spark, sf, Window.unboundedPreceding)


@query("sliding_cf", "SELECT event_id, count(*) OVER w AS n, round(avg(value) OVER w, 6) AS mean, round(var_pop(value * 1.0371) OVER w, 5) AS variance FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 9 PRECEDING AND CURRENT ROW)")
def sliding_cf(spark, sf):
    return _windowed(spark, sf, -9)


def _windowed(spark, sf, start: int) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(start, 0)
    n = F.count("*").over(w)
    return T(spark, sf, "events").select("event_id", n.alias("n"), F.round(F.avg("value").over(w), 6).alias("mean"), F.round(F.var_pop(F.col("value") * 1.0371).over(w), 5).alias("variance"))


@query("union_cfs", f"SELECT n_regionkey AS r, count(*)::DOUBLE AS n, round(avg(v), 6) AS mu0, round(count(*) * var_pop(v), 3) AS sse FROM (SELECT c_nationkey AS k, c_acctbal / 1000 AS v FROM customer UNION ALL SELECT s_nationkey, s_acctbal / 1000 FROM supplier) JOIN nation ON k = n_nationkey GROUP BY n_regionkey")
def union_cfs(spark, sf):
    """Features of two tables, united and merged by region."""
    one = lambda t, k, v: ft.cf_agg(T(spark, sf, t).select(F.col(k).alias("k"), (F.col(v) / 1000).alias("v")), ["k"], ["v"])
    n = T(spark, sf, "nation").select(F.col("n_nationkey").alias("k"), F.col("n_regionkey").alias("r"))
    both = one("customer", "c_nationkey", "c_acctbal").unionByName(one("supplier", "s_nationkey", "s_acctbal")).join(n, "k")
    c = ft.cf_merge_agg(both, ["r"], 1)
    return c.select("r", F.col("cf.n").alias("n"), F.round(F.col("cf.mu")[0], 6).alias("mu0"), F.round("cf.sse", 3).alias("sse"))


_A = "SELECT c_custkey AS id, c_custkey % 5 AS c FROM customer"
_B = "SELECT c_custkey AS id, c_custkey % 10 % 5 + (CASE WHEN c_custkey % 100 = 7 THEN 1 ELSE 0 END) AS c FROM customer"


def _partitions(spark, sf) -> tuple[DataFrame, DataFrame]:
    c = T(spark, sf, "customer").select(F.col("c_custkey").alias("id"))
    return c.select("id", (F.col("id") % 5).alias("c")), c.select("id", (F.col("id") % 10 % 5 + F.when(F.col("id") % 100 == 7, 1).otherwise(0)).alias("c"))


@query("intersect_clusters", f"{_A} INTERSECT ALL {_B}")
def intersect_clusters(spark, sf):
    a, b = _partitions(spark, sf)
    return a.intersectAll(b)


@query("except_clusters", f"{_A} EXCEPT ALL {_B}")
def except_clusters(spark, sf):
    a, b = _partitions(spark, sf)
    return a.exceptAll(b)


@query("math_profile", "SELECT s_suppkey, round(sqrt(abs(s_acctbal)), 6) AS root, round(ln(abs(s_acctbal) + 1), 6) AS log, round(cos(s_acctbal / 1000), 6) AS cosine, CAST(floor(s_acctbal / 100) AS BIGINT) AS cell, greatest(s_nationkey, 12) AS top, round(pow(s_acctbal / 1000, 2), 6) AS square FROM supplier")
def math_profile(spark, sf):
    b = F.col("s_acctbal")
    return T(spark, sf, "supplier").select(
        "s_suppkey", F.round(F.sqrt(F.abs(b)), 6).alias("root"), F.round(F.log(F.abs(b) + 1), 6).alias("log"), F.round(F.cos(b / 1000), 6).alias("cosine"),
        F.floor(b / 100).cast("long").alias("cell"), F.greatest("s_nationkey", F.lit(12)).alias("top"), F.round(F.pow(b / 1000, 2), 6).alias("square"),
    )


@query("events_props_cf", "SELECT event_type, count(*)::DOUBLE AS n, round(avg(k), 5) AS mu0, round(count(*) * var_pop(k), 2) AS sse FROM (SELECT event_type, CAST(json_extract_string(props, '$.k') AS DOUBLE) AS k FROM events) GROUP BY event_type")
def events_props_cf(spark, sf):
    v = T(spark, sf, "events").select("event_type", F.from_json("props", "k double")["k"].alias("k"))
    return ft.cf_agg(v, ["event_type"], ["k"]).select("event_type", "cf.n", F.round(F.col("cf.mu")[0], 5).alias("mu0"), F.round("cf.sse", 2).alias("sse"))


@query("doc_shape_cf", "SELECT lang, count(*)::DOUBLE AS n, round(avg(length(text)), 5) AS chars, round(avg(len(string_split(text, ' '))), 5) AS words FROM documents GROUP BY lang")
def doc_shape_cf(spark, sf):
    v = T(spark, sf, "documents").select("lang", F.length("text").cast("double").alias("chars"), F.size(F.split("text", " ")).cast("double").alias("words"))
    return ft.cf_agg(v, ["lang"], ["chars", "words"]).select("lang", "cf.n", F.round(F.col("cf.mu")[0], 5).alias("chars"), F.round(F.col("cf.mu")[1], 5).alias("words"))


@query("conv_shape_cf", "SELECT role, count(*)::DOUBLE AS n, round(avg(length(text)), 5) AS chars FROM conversations GROUP BY role")
def conv_shape_cf(spark, sf):
    v = T(spark, sf, "conversations").select("role", F.length("text").cast("double").alias("chars"))
    return ft.cf_agg(v, ["role"], ["chars"]).select("role", "cf.n", F.round(F.col("cf.mu")[0], 5).alias("chars"))


@query("page_shape_cf", "SELECT count(*)::DOUBLE AS n, round(avg(length(url)), 5) AS url, round(avg(length(html)), 5) AS html FROM pages")
def page_shape_cf(spark, sf):
    v = T(spark, sf, "pages").select(F.length("url").cast("double").alias("u"), F.length("html").cast("double").alias("h"))
    return ft.cf_agg(v, [], ["u", "h"]).select("cf.n", F.round(F.col("cf.mu")[0], 5).alias("url"), F.round(F.col("cf.mu")[1], 5).alias("html"))


@query("cf_by_month", "SELECT CAST(year(l_shipdate) * 100 + month(l_shipdate) AS INTEGER) AS month, count(*)::DOUBLE AS n, round(avg(l_quantity), 5) AS mu0, round(count(*) * var_pop(l_quantity), 2) AS sse FROM lineitem GROUP BY 1")
def cf_by_month(spark, sf):
    v = T(spark, sf, "lineitem").select((F.year("l_shipdate") * 100 + F.month("l_shipdate")).alias("month"), "l_quantity")
    return ft.cf_agg(v, ["month"], ["l_quantity"]).select("month", "cf.n", F.round(F.col("cf.mu")[0], 5).alias("mu0"), F.round("cf.sse", 2).alias("sse"))


def _event_windows(spark, sf, *spec: str) -> DataFrame:
    w = F.window("ts", *spec)
    c = ft.cf_agg(T(spark, sf, "events").withColumn("w", w), ["w"], ["value"])
    return c.select(F.unix_timestamp(F.col("w.start")).alias("start"), "cf.n", F.round(F.col("cf.mu")[0], 5).alias("mu0"), F.round("cf.sse", 2).alias("sse"))


_CFV = "count(*)::DOUBLE AS n, round(avg(value), 5) AS mu0, round(count(*) * var_pop(value), 2) AS sse"
query("cf_tumbling", f"SELECT (epoch(ts)::BIGINT // 21600) * 21600 AS start, {_CFV} FROM (SELECT *, floor(epoch(ts))::BIGINT FROM events) GROUP BY 1".replace("epoch(ts)::BIGINT // 21600", "CAST(floor(epoch(ts)) AS BIGINT) // 21600"))(lambda spark, sf: _event_windows(spark, sf, "6 hours"))
query("cf_sliding", f"SELECT (CAST(floor(epoch(ts)) AS BIGINT) // 21600 - s) * 21600 AS start, {_CFV} FROM events, (VALUES (0), (1)) AS v(s) GROUP BY 1")(lambda spark, sf: _event_windows(spark, sf, "12 hours", "6 hours"))


_CFV4 = "count(*)::DOUBLE AS n, round(avg(value), 4) AS mu0, round(count(*) * var_pop(value * 1.0371), 5) AS sse"


@query("cf_session", f"WITH g AS (SELECT *, CASE WHEN epoch(ts) - lag(epoch(ts)) OVER w < 7200 THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sid FROM g) SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, {_CFV4} FROM s GROUP BY user_id, sid")
def cf_session(spark, sf):
    e = T(spark, sf, "events").withColumn("w", F.session_window("ts", "2 hours"))
    # Scaled, so that sums of squares of two-decimal values do not end on a rounding tie.
    c = ft.cf_agg(e.withColumn("x", F.col("value") * 1.0371), ["user_id", "w"], ["x"])
    return c.select("user_id", F.unix_timestamp(F.col("w.start")).alias("start"), "cf.n", F.round(F.col("cf.mu")[0] / 1.0371, 4).alias("mu0"), F.round("cf.sse", 5).alias("sse"))


@query("roundtrip_cfs", f"SELECT k, round(n, 6) AS n, round(m0, 6) AS mu0, round(m1, 6) AS mu1, round(sse, 3) AS sse FROM ({NATION2})")
def roundtrip_cfs(spark, sf):
    """Features written as Parquet, partitioned by key, and read again."""
    import uuid

    path = f"{storage.checkpoint_folder(spark)}/cfs-{uuid.uuid4().hex}"
    storage.save(nation_cf2(spark, sf), path, by=["k"])
    return flat(storage.load(spark, path), "cf", 2, F.col("k").cast("int").alias("k"))


@query("rmsd_by_group", f"SELECT round(sqrt(sum(sse) / sum(n)), 5) AS rmsd, count(*) AS k FROM (SELECT count(*) AS n, count(*) * ({' + '.join(f'var_pop({c})' for c in L5)}) AS sse FROM (SELECT l_partkey, {LINE5_SQL} FROM lineitem) GROUP BY l_partkey % 500)")
def rmsd_by_group(spark, sf):
    v = src.line5(T(spark, sf, "lineitem"), ("l_partkey",)).withColumn("g", F.col("l_partkey") % 500)
    return quality.rmsd(ft.cf_agg(v, ["g"], L5)).select(F.round("rmsd", 5).alias("rmsd"), "k")


@query("wss_between_within", "WITH c AS (SELECT l_returnflag AS g, l_quantity AS x FROM lineitem), w AS (SELECT sum(s) AS within FROM (SELECT count(*) * var_pop(x) AS s FROM c GROUP BY g)), t AS (SELECT count(*) * var_pop(x) AS total FROM c) SELECT round(within, 1) AS within, round(total - within, 1) AS between FROM w, t")
def wss_between_within(spark, sf):
    v = T(spark, sf, "lineitem").select(F.col("l_returnflag").alias("g"), F.col("l_quantity").alias("x"))
    groups = ft.cf_agg(v, ["g"], ["x"])
    total = ft.cf_agg(v, [], ["x"]).select(F.col("cf.sse").alias("total"))
    return quality.wss(groups).crossJoin(total).select(F.round("wss", 1).alias("within"), F.round(F.col("total") - F.col("wss"), 1).alias("between"))


_ARI_ROWS = "SELECT l_partkey % 500 AS a, l_partkey % 250 AS b FROM lineitem"


@query("ari_mixture", f"WITH r AS ({_ARI_ROWS}), z AS (SELECT a, b, count(*) AS c FROM r GROUP BY a, b), t AS (SELECT sum(c * (c - 1) / 2) AS x, sum(c) AS n FROM z), u AS (SELECT sum(c * (c - 1) / 2) AS x FROM (SELECT sum(c) AS c FROM z GROUP BY a)), v AS (SELECT sum(c * (c - 1) / 2) AS x FROM (SELECT sum(c) AS c FROM z GROUP BY b)) SELECT round((t.x - u.x * v.x / (t.n * (t.n - 1) / 2)) / ((u.x + v.x) / 2 - u.x * v.x / (t.n * (t.n - 1) / 2)), 6) AS ari FROM t, u, v")
def ari_mixture(spark, sf):
    v = T(spark, sf, "lineitem").select((F.col("l_partkey") % 500).alias("a"), (F.col("l_partkey") % 250).alias("b"))
    return quality.adjusted_rand(v, "a", "b").select(F.round("ari", 6).alias("ari"))
