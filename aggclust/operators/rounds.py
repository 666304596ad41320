"""Agglomeration as rounds of DataFrame joins, for hierarchies larger than one task."""

from __future__ import annotations

from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from aggclust.functions import linkage as link
from aggclust.functions.features import gap, square_norm
from aggclust.sources.storage import cut_lineage


def pairs_within_eps(points: DataFrame, d: int, eps: float) -> DataFrame:
    """i < j and their distance, for pairs of points (id, vec) within ``eps``.

    A grid of side ``eps`` puts partners into the same or adjoining cells: one side is sent to all
    3^d cells around its own, and an equi-join on the cell replaces the nested loop.
    """
    cell = F.array(*(F.floor(F.col("vec")[i] / eps).cast("long") for i in range(d)))
    home = points.select(F.col("id").alias("j"), F.col("vec").alias("y"), cell.alias("cell"))
    steps = F.array(*(F.array(*(F.lit(s).cast("long") for s in step)) for step in product((-1, 0, 1), repeat=d)))
    around = points.select(F.col("id").alias("i"), F.col("vec").alias("x"), F.explode(F.transform(steps, lambda s: F.zip_with(cell, s, lambda a, b: a + b))).alias("cell"))
    dist = F.sqrt(square_norm(gap(F.col("x"), F.col("y"))))
    return around.join(home, "cell").where("i < j").select("i", "j", dist.alias("d")).where(F.col("d") <= eps)


def nearest_neighbours(pairs: DataFrame) -> DataFrame:
    """node, other, d: everyone's nearest by (d, smaller id, larger id), from pairs (i, j, d)."""
    both = pairs.select(F.col("i").alias("u"), F.col("j").alias("v"), "d").unionByName(pairs.select(F.col("j").alias("u"), F.col("i").alias("v"), "d"))
    order = F.struct("d", F.least("u", "v"), F.greatest("u", "v"))
    return both.groupBy("u").agg(F.min_by(F.struct("v", "d"), order).alias("best")).select("u", "best.v", "best.d")


def reciprocal_rounds(pairs: DataFrame, sizes: DataFrame, linkage: str, approximate: bool = False) -> DataFrame:
    """Merges (a, b, height, size) of a full pair table (i < j, d) and sizes (id, n), many at a time.

    Every mutually nearest pair merges in each round, which equals the greedy order for reducible
    linkages; others are refused unless ``approximate``.  A cluster keeps its smallest member's id.
    """
    if not link.get(linkage).reducible and not approximate:
        raise ValueError(f"{linkage} is not reducible")
    n = lambda end: sizes.select(F.col("id").alias(end), F.col("n").cast("double").alias(f"n{end}"))
    full = pairs.join(n("i"), "i").join(n("j"), "j")
    ends = lambda x, y: full.select(F.col(x).alias("u"), F.col(f"n{x}").alias("nu"), F.col(y).alias("v"), F.col(f"n{y}").alias("nv"), F.col("d").cast("double").alias("d"))
    both = cut_lineage(ends("i", "j").unionByName(ends("j", "i")))
    found = None
    while True:
        order = F.struct("d", F.least("u", "v"), F.greatest("u", "v"))
        near = both.groupBy("u").agg(F.min_by(F.struct("v", "d", "nu", "nv"), order).alias("x")).select("u", "x.*")
        back = near.select(F.col("u").alias("v"), F.col("v").alias("u"))
        pick = near.join(back, ["u", "v"]).where("u < v")
        pick = cut_lineage(pick.select(F.col("u").alias("a"), F.col("v").alias("b"), F.col("d").alias("dab"), F.col("nu").alias("na"), F.col("nv").alias("nb")))
        if pick.isEmpty():
            return found if found is not None else pick.select("a", "b", F.col("dab").alias("height"), F.col("na").alias("size"))
        step = pick.select("a", "b", F.col("dab").alias("height"), (F.col("na") + F.col("nb")).alias("size"))
        found = step if found is None else found.unionByName(step)
        # First the near ends of all pairs, then the far ends, each by the recurrence.
        turned = _fold(both, pick, linkage).select(F.col("v").alias("u"), F.col("nv").alias("nu"), F.col("u").alias("v"), F.col("nu").alias("nv"), "d")
        both = cut_lineage(_fold(turned, pick, linkage))


def _fold(both: DataFrame, pick: DataFrame, linkage: str) -> DataFrame:
    """Replace the ends ``u`` that merge by their union."""
    ends = pick.select(F.col("a").alias("u"), F.lit(0).alias("side"), "*").unionByName(pick.select(F.col("b").alias("u"), F.lit(1).alias("side"), "*"))
    joined = both.join(ends, "u", "left").where("a IS NULL OR (v <> a AND v <> b)")
    rows = joined.groupBy(F.coalesce("a", "u").alias("u"), "v").agg(
        F.max(F.when(F.coalesce("side", F.lit(0)) == 0, F.col("d"))).alias("da"),
        F.max(F.when(F.col("side") == 1, F.col("d"))).alias("db"),
        *(F.max(c).alias(c) for c in ("dab", "na", "nb", "nu", "nv")),
    )
    new = link.recur(linkage, F.col("da"), F.col("db"), F.col("dab"), F.col("na"), F.col("nb"), F.col("nv"))
    merged = F.col("db").isNotNull()
    return rows.select("u", F.when(merged, F.col("na") + F.col("nb")).otherwise(F.col("nu")).alias("nu"), "v", "nv", F.when(merged, new).otherwise(F.col("da")).alias("d"))


def single_by_forest(pairs: DataFrame) -> DataFrame:
    """The edges (i, j, d) of a minimum spanning forest: single linkage's merges, in any order.

    In each round every component takes its lightest outgoing edge (ties by ids) and hooks onto
    the component behind it; pointers are shortened until they rest.
    """
    pairs = cut_lineage(pairs.select("i", "j", "d"))
    label = cut_lineage(pairs.select(F.col("i").alias("id")).union(pairs.select("j")).distinct().select("id", F.col("id").alias("c")))
    taken = None
    while True:
        ci, cj = label.select(F.col("id").alias("i"), F.col("c").alias("ci")), label.select(F.col("id").alias("j"), F.col("c").alias("cj"))
        out = cut_lineage(pairs.join(ci, "i").join(cj, "j").where("ci <> cj").select("i", "j", "d", "ci", "cj"))
        if out.isEmpty():
            return taken if taken is not None else pairs.limit(0)
        edge = F.struct("d", "i", "j")
        ends = out.select(F.col("ci").alias("c"), F.col("cj").alias("to"), edge.alias("e")).unionByName(out.select(F.col("cj").alias("c"), F.col("ci").alias("to"), edge.alias("e")))
        best = cut_lineage(ends.groupBy("c").agg(F.min_by(F.struct("to", "e"), "e").alias("best")).select("c", "best.to", "best.e"))
        chosen = best.select("e.i", "e.j", "e.d").distinct()
        taken = chosen if taken is None else taken.unionByName(chosen)
        # Two that chose each other: the smaller is the root.
        other = best.select(F.col("c").alias("to"), F.col("to").alias("back"))
        point = cut_lineage(best.join(other, "to", "left").select("c", F.when((F.col("back") == F.col("c")) & (F.col("c") < F.col("to")), F.col("c")).otherwise(F.col("to")).alias("p")))
        while True:
            up = point.select(F.col("c").alias("p"), F.col("p").alias("g"))
            moved = cut_lineage(point.join(up, "p", "left").select("c", F.coalesce("g", "p").alias("p"), (F.coalesce("g", "p") != F.col("p")).alias("moved")))
            point = moved.select("c", "p")
            if moved.where("moved").isEmpty():
                break
        pairs = out.select("i", "j", "d")
        label = cut_lineage(label.join(point, "c", "left").select("id", F.coalesce("p", "c").alias("c")))
