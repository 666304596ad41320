"""Connected components of a link table, without collecting links or labels."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from aggclust.llm.batches import cut, release


def components(links: DataFrame) -> DataFrame:
    """(node, component) for every node of ``links`` (a, b); the component is its smallest node.

    Every node points to a smaller-or-equal node of its component.  A round hooks each node, and
    the node it points to, onto the smallest grandparent among its neighbours and shortens its own
    path, so the number of rounds is logarithmic in the longest path.  Rounds aggregate minima
    before they shuffle, so a hub costs one row per task; each round's table is written to the
    shared checkpoint folder, and the sum of the pointers tells when nothing moved.
    """
    both = links.select(F.col("a").alias("u"), F.col("b").alias("v")).where("u <> v")
    both = cut(both.unionByName(both.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct())
    point = cut(both.groupBy("u").agg(F.min("v").alias("p")).select(F.col("u").alias("node"), F.least("u", "p").alias("p")))
    total = None
    while True:
        now = point.agg(F.sum(F.col("p").cast("decimal(38,0)"))).first()[0]
        if now == total:
            return point.select("node", F.col("p").alias("component"))
        total = now
        top = point.select(F.col("node").alias("p"), F.col("p").alias("g"))
        grand = point.join(top, "p").select("node", "p", "g")
        seen = both.join(grand.select(F.col("node").alias("v"), "g"), "v").groupBy("u").agg(F.min("g").alias("g"))
        hooked = seen.join(point.withColumnRenamed("node", "u"), "u")
        moves = (
            grand.select("node", F.least("p", "g").alias("p"))
            .unionByName(hooked.select(F.col("u").alias("node"), F.col("g").alias("p")))
            .unionByName(hooked.select(F.col("p").alias("node"), F.col("g").alias("p")))
        )
        point = cut(moves.groupBy("node").agg(F.min("p").alias("p")))
        del top, grand, seen, hooked, moves
        release(point.sparkSession)
