"""Mixing sources to target weights by Pareto order sampling.

Sources get targets in words: ``volume`` times all words, shared by weight and stopped at
``repeats`` times a source's own words, the rest reshared (water filling, in closed form over the
sources sorted by the share at which each is full).  With r = target / words, every document of a
source is taken floor(r) times for certain; the remaining words come from a Pareto sample of fixed
size in words and unequal probabilities: a document's inclusion odds grow with its size (with
the power ``lean`` of the largest power of two in it; 0 makes them equal), and their scale is solved for in
each source so that the expected words are the words wanted.  A document's rank is the odds of its
random number over its inclusion odds, and documents are taken by rank until the words are
reached.  As long documents tend to come early, the last one taken tends to be short.  The ranks'
histogram gives each source's cut; only the documents of the cut's bin are put in exact order, so
no source, however large, meets in one task.

The document at which the words are reached is taken if that comes nearer to the target than
leaving it, so a source's words differ from its target by at most half of one document.

Defined cases: a null text has no words and is taken 0 words, with the inclusion odds of one word;
a null source is one source, sorted last; random numbers depend on id and seed alone, so reruns
agree; rows of one id are ordered by size, and equal ones are all taken or all left; a source
without words has target 0; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from aggclust.llm.batches import cut, documents
from aggclust.llm.sharding import MULTIPLIERS, OFFSETS, PRIME, mixed

WEIGHTS, VOLUME, REPEATS, LEAN, BINS, SEED, FEW = (3.0, 1.0, 2.0), 1.5, 2.0, 0.5, 4096, 7, 100_000
#: Halvings of the interval, in powers of two, that holds the scale of a source's inclusion odds.
HALVINGS, WIDEST = 80, 80
WORD = r"[^\x20\x09-\x0D]+"


def words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text.cast("string"), F.lit(WORD)), F.lit(0)).cast("long")


def allocate(sources: DataFrame, weights: tuple = WEIGHTS, volume: float = VOLUME, repeats: float = REPEATS) -> DataFrame:
    """``source_size`` per ``source`` -> also weight, target, whole, left (a row per source).

    The window runs over sources, of which the table has one row each after aggregation.
    """
    everything = Window.partitionBy(F.lit(0))
    by_name = everything.orderBy(F.col("source").asc_nulls_last())
    full_at = everything.orderBy("_full", F.col("source").asc_nulls_last())
    before = full_at.rowsBetween(Window.unboundedPreceding, -1)
    w = F.element_at(F.array(*map(F.lit, weights)), (F.pmod(F.row_number().over(by_name) - 1, F.lit(len(weights))) + 1).cast("int"))
    out = sources.withColumn("weight", w).withColumn("_full", repeats * F.col("source_size") / F.col("weight"))
    # If all that fill up earlier are full, each other source gets this much per weight.
    rest = volume * F.sum("source_size").over(everything) - repeats * F.coalesce(F.sum("source_size").over(before), F.lit(0))
    level = rest / (F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
    out = out.withColumn("_rank", F.row_number().over(full_at)).withColumn("_level", level)
    # The level is that of the first source that does not fill up.
    not_full = F.col("_full") > F.col("_level")
    out = out.withColumn("_level", F.min_by("_level", F.when(not_full, F.col("_rank"))).over(everything))
    target = F.when(F.col("_level").isNull(), repeats * F.col("source_size")).otherwise(F.least(repeats * F.col("source_size"), F.col("weight") * F.col("_level")))
    out = out.withColumn("target", F.round(target, 6))
    out = out.withColumn("whole", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long"))
    return out.withColumn("left", F.col("target") - F.col("whole") * F.col("source_size")).drop("_full", "_level", "_rank")


def random_number(key: Column, seed: int) -> Column:
    return mixed(F.coalesce(key.cast("long"), F.lit(0).cast("long")), seed)


def odds_weight(size_class: Column, lean: float) -> Column:
    """What a document's inclusion odds are multiplied by; a root is the same in every SQL engine."""
    base = F.pow(F.lit(2.0), size_class.cast("double"))
    return F.sqrt(base) if lean == 0.5 else F.pow(base, F.lit(lean))


#: The scale at which the expected words of ``classes`` (w, words) are the words in ``left``.
SCALE = f"""aggregate(sequence(1, {HALVINGS}), named_struct('lo', -{WIDEST}D, 'hi', {WIDEST}D), (a, i) ->
    CASE WHEN aggregate(classes, 0D, (s, x) -> s + x.words * (1D - 1D / (1D + pow(2D, (a.lo + a.hi) / 2) * x.w))) < left
    THEN named_struct('lo', (a.lo + a.hi) / 2, 'hi', a.hi) ELSE named_struct('lo', a.lo, 'hi', (a.lo + a.hi) / 2) END,
    a -> pow(2D, (a.lo + a.hi) / 2))"""


def scales(rows: DataFrame, weights: tuple = WEIGHTS, volume: float = VOLUME, repeats: float = REPEATS) -> DataFrame:
    """What ``allocate`` gives per source, and the scale of its inclusion odds; rows have source, size, c and w."""
    classes = cut(rows.groupBy("source", "c", "w").agg(F.sum("size").alias("words")))
    # A source has at most 64 classes of sizes.
    per = classes.groupBy("source").agg(F.sum("words").alias("source_size"), F.array_sort(F.collect_list(F.struct("c", "w", F.col("words").cast("double").alias("words")))).alias("classes"))
    shared = allocate(per, weights, volume, repeats)
    return cut(shared.withColumn("scale", F.when(F.col("left") > 0, F.expr(SCALE)).otherwise(F.lit(1.0))).drop("classes"))


def _ranked(rows: DataFrame, per_source: DataFrame) -> DataFrame:
    """``rows`` with their source's columns, inclusion probability, rank, and the rank's bin."""
    joined = rows.join(hinted(per_source.withColumnRenamed("source", "_s")), rows["source"].eqNullSafe(F.col("_s"))).drop("_s")
    odds = F.col("scale") * F.col("w")
    u = F.col("u").cast("double")
    rank = u / (F.lit(float(PRIME)) - u) / odds
    joined = joined.withColumns({"inclusion": F.when(F.col("left") > 0, odds / (odds + 1)).otherwise(0.0), "rank": rank})
    return joined.withColumn("bin", F.least(F.floor(F.col("rank") / (F.col("rank") + 1) * BINS), F.lit(BINS - 1)).cast("int"))


def decide(rows: DataFrame, weights: tuple = WEIGHTS, volume: float = VOLUME, repeats: float = REPEATS) -> DataFrame:
    """What each source takes, from rows (doc_id, source, size, u, c, w).

    The result has a row per source: source_size, target, whole, left, scale, and the cut as a bin
    of ranks and, inside it, as the last key taken.
    """
    sources = scales(rows, weights, volume, repeats)
    binned = _ranked(rows, sources.select("source", "left", "scale"))
    hist = binned.groupBy("source", "bin").agg(F.sum("size").alias("words"))
    upto = Window.partitionBy("source").orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
    hist = hist.withColumn("after", F.sum("words").over(upto))
    known = sources.withColumnRenamed("source", "_s")
    crossed = hist.join(known, hist["source"].eqNullSafe(known["_s"])).where(F.col("after") > F.col("left")).groupBy("source")
    cuts = crossed.agg(F.min("bin").alias("cut_bin"), F.min_by(F.col("after") - F.col("words"), "bin").alias("before"))
    cuts = sources.withColumnRenamed("source", "_s").join(cuts, F.col("_s").eqNullSafe(F.col("source")), "left").drop("source").withColumnRenamed("_s", "source")
    cuts = cut(cuts.withColumn("cut_bin", F.coalesce("cut_bin", F.lit(BINS))))
    # The bins of the cuts hold a small share of the rows; they alone are put in order.
    at = cuts.select(F.col("source").alias("_s"), "cut_bin", "before")
    inside = binned.join(hinted(at), binned["source"].eqNullSafe(F.col("_s")) & (F.col("bin") == F.col("cut_bin")))
    keys = inside.groupBy("source", "rank", "doc_id", "size", "before", "left").agg(F.sum("size").alias("words"))
    order = Window.partitionBy("source").orderBy("rank", F.col("doc_id").asc_nulls_first(), "size").rowsBetween(Window.unboundedPreceding, 0)
    keys = keys.withColumn("after", F.col("before") + F.sum("words").over(order))
    # Taken if that comes nearer to the words wanted than leaving it.
    last = keys.where((F.col("left") > 0) & (2 * F.col("after") - F.col("words") <= 2 * F.col("left"))).groupBy("source").agg(F.max(_key()).alias("cut_key"))
    last = last.withColumnRenamed("source", "_s")
    out = cuts.join(last, F.col("source").eqNullSafe(F.col("_s")), "left")
    return cut(out.select("source", "source_size", "target", "whole", "left", "scale", "cut_bin", "cut_key"))


def _key() -> Column:
    return F.struct("rank", F.coalesce("doc_id", F.lit(-(2**63))).alias("id"), "size")


def hinted(sources: DataFrame) -> DataFrame:
    """Broadcast a frame of a row per source if they are few; else the join shuffles, and AQE splits hot sources."""
    return F.broadcast(sources) if sources.count() <= FEW else sources


def with_copies(rows: DataFrame, decided: DataFrame) -> DataFrame:
    """``rows`` (doc_id, source, size, u, c, w and others) with source_size, target, inclusion, rank and copies."""
    ranked = _ranked(rows, decided)
    drawn = (F.col("left") > 0) & ((F.col("bin") < F.col("cut_bin")) | ((F.col("bin") == F.col("cut_bin")) & (_key() <= F.col("cut_key"))))
    copies = F.col("whole") + F.when(drawn, 1).otherwise(0)
    return ranked.withColumn("copies", copies.cast("long")).drop("whole", "left", "scale", "bin", "cut_bin", "cut_key")


def _sized(rows: DataFrame, seed: int, lean: float) -> DataFrame:
    """doc_id, source and size with the random number, the class of the size and its weight."""
    c = F.length(F.bin(F.greatest("size", F.lit(1)))) - 1
    return rows.withColumns({"u": random_number(F.col("doc_id"), seed), "c": c}).withColumn("w", odds_weight(F.col("c"), lean))


def sized(docs: DataFrame, seed: int, id_col: str, text_col: str, source_col: str, lean: float = LEAN) -> DataFrame:
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(source_col).cast("string").alias("source"), words(F.col(text_col)).alias("size"))
    return _sized(rows, seed, lean)


def mix(docs: DataFrame, seed: int = SEED, weights: tuple = WEIGHTS, volume: float = VOLUME, repeats: float = REPEATS, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", lean: float = LEAN) -> DataFrame:
    """doc_id, size, source_size, target, taken, copies, inclusion and rank of every row."""
    rows = cut(sized(docs, seed, id_col, text_col, source_col, lean))
    out = with_copies(rows, decide(rows, weights, volume, repeats))
    return out.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"), "copies", "inclusion", "rank")


def repeat(docs: DataFrame, seed: int = SEED, weights: tuple = WEIGHTS, volume: float = VOLUME, repeats: float = REPEATS, lean: float = LEAN) -> DataFrame:
    """``docs`` as the mix takes them: each row as often as it has copies, all columns."""
    decided = decide(cut(sized(docs, seed, "doc_id", "text", "source", lean)), weights, volume, repeats)
    own = docs.select(F.struct("*").alias("_row"), F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), words(F.col("text")).alias("size"))
    taken = with_copies(_sized(own, seed, lean), decided).where(F.col("copies") > 0)
    repeated = taken.select("_row", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))))
    return repeated.select(*(F.col("_row").getField(c).alias(c) for c in docs.columns))


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(documents(spark, sf_dir)).withColumn("inclusion", F.round("inclusion", 6)).drop("rank")


def oracle() -> str:
    """The definition in SQL: the scale by halving, ranks per row, and running words in their order."""
    name = f"CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % {len(WEIGHTS)} " + " ".join(f"WHEN {i} THEN {x}" for i, x in enumerate(WEIGHTS)) + " END"
    steps = f"SELECT doc_id, source, size, coalesce(doc_id, 0) % {PRIME} AS h FROM sized"
    for i in range(3):
        steps = f"SELECT doc_id, source, size, (h * h + (h * {MULTIPLIERS[i]}) % {PRIME} + {(OFFSETS[i] + SEED * (i + 1)) % PRIME}) % {PRIME} AS h FROM ({steps})"
    middle = "(s.lo + s.hi) / 2"
    expected = f"list_sum(list_transform(t.classes, lambda x: x.words * (1 - 1 / (1 + pow(2.0, {middle}) * x.w))))"
    return f"""
WITH RECURSIVE sized AS (SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size FROM documents),
drawn AS (SELECT *, CAST(h AS DOUBLE) / ({PRIME} - CAST(h AS DOUBLE)) AS odds, sqrt(pow(2.0, length(bin(greatest(size, 1))) - 1)) AS w FROM ({steps})),
sets AS (SELECT source, w, sum(size) AS words FROM drawn GROUP BY source, w),
per AS (SELECT source, CAST(sum(words) AS BIGINT) AS source_size, list(struct_pack(w := w, words := CAST(words AS DOUBLE)) ORDER BY w) AS classes FROM sets GROUP BY source),
weighted AS (SELECT *, CAST({name} AS DOUBLE) AS weight FROM per),
filled AS (SELECT *, {REPEATS} * source_size / weight AS full_at FROM weighted),
levels AS (SELECT *, ({VOLUME} * sum(source_size) OVER () - {REPEATS} * coalesce(sum(source_size) OVER before, 0))
    / (sum(weight) OVER () - coalesce(sum(weight) OVER before, 0)) AS lvl, row_number() OVER (ORDER BY full_at, source NULLS LAST) AS rk FROM filled
    WINDOW before AS (ORDER BY full_at, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
one AS (SELECT arg_min(lvl, rk) FILTER (WHERE full_at > lvl) AS lvl FROM levels),
targets AS (SELECT source, source_size, classes, round(CASE WHEN one.lvl IS NULL THEN {REPEATS} * source_size ELSE least({REPEATS} * source_size, weight * one.lvl) END, 6) AS target FROM levels, one),
wholes AS (SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target / source_size) AS BIGINT) ELSE 0 END AS whole FROM targets),
rests AS (SELECT *, target - whole * source_size AS rest FROM wholes),
solve(source, lo, hi, i) AS (SELECT source, -{WIDEST}.0::DOUBLE, {WIDEST}.0::DOUBLE, 0 FROM rests UNION ALL
    SELECT s.source, CASE WHEN {expected} < t.rest THEN {middle} ELSE s.lo END, CASE WHEN {expected} < t.rest THEN s.hi ELSE {middle} END, s.i + 1
    FROM solve s JOIN rests t ON s.source IS NOT DISTINCT FROM t.source WHERE s.i < {HALVINGS}),
scaled AS (SELECT r.*, CASE WHEN rest > 0 THEN pow(2.0, (lo + hi) / 2) ELSE 1.0 END AS scale FROM rests r JOIN solve v ON r.source IS NOT DISTINCT FROM v.source AND v.i = {HALVINGS}),
ranks AS (SELECT d.doc_id, d.source, d.size, source_size, target, whole, rest, scale * w AS inclusion_odds, odds / (scale * w) AS rank
    FROM drawn d JOIN scaled c ON d.source IS NOT DISTINCT FROM c.source),
taking AS (SELECT *, sum(size) OVER (PARTITION BY source ORDER BY rank, doc_id NULLS FIRST, size) AS after_it, sum(size) OVER (PARTITION BY source, rank, doc_id, size) AS own FROM ranks),
copied AS (SELECT *, whole + CASE WHEN rest > 0 AND 2 * after_it - own <= 2 * rest THEN 1 ELSE 0 END AS n FROM taking)
SELECT doc_id, size, source_size, target, CAST(size * n AS BIGINT) AS taken, CAST(n AS BIGINT) AS copies,
    round(CASE WHEN rest > 0 THEN inclusion_odds / (inclusion_odds + 1) ELSE 0 END, 6) AS inclusion FROM copied"""


