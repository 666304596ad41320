"""Reproducible shuffle and sharding by a Feistel permutation over global row numbers.

Rows get global numbers 0..N-1 in the order of a mixed hash of their id: the hash's high bits name
a bin, one aggregation counts the bins, and only the slim rows (id, size, checksum) meet in a
window per bin.  No window spans the table and no text is shuffled.  A generalised Feistel
network over a grid a x b >= N, with cycle walking back below N, permutes the numbers; the
permuted number p goes to shard p mod k, slot p div k.  Shards therefore differ by one row at
most (law ``rows``), and anyone who knows N, the seed and a row's number can compute its place.

Defined cases: a null text has size 1 and the checksum of no bytes; a null id is hashed as 0;
repeated ids are ordered by checksum and size, and whole repeated rows share their places in any
order; an empty table gives no rows.  Other columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from aggclust.llm.batches import cut, documents

#: A prime below 2^31, so that products of two remainders fit a long.
PRIME = 2147483647
WALKS = 64
# Multipliers and offsets of the rounds, any residues of PRIME.
MULTIPLIERS = (1103515245, 1664525, 22695477, 134775813, 214013, 69069)
OFFSETS = (12345, 1013904223, 1, 907633385, 2531011, 362437)


def mixed(x: Column, seed: int) -> Column:
    """A hash below PRIME from arithmetic that SQL engines share: three squarings of an affine map."""
    h = F.pmod(x, F.lit(PRIME).cast("long"))
    for i in range(3):
        h = F.pmod(h * h + h * F.lit(MULTIPLIERS[i]).cast("long") % PRIME + F.lit((OFFSETS[i] + seed * (i + 1)) % PRIME), F.lit(PRIME).cast("long"))
    return h


def grid(n: int) -> tuple[int, int]:
    """Sides a, b of the Feistel grid: a * b >= n with fewer than a cells to spare."""
    a = max(2, math.isqrt(max(n - 1, 0)) + 1)
    return a, max(2, -(-n // a))


def feistel(x: str, a: int, b: int, seed: int) -> str:
    """SQL for one pass of the network on ``x`` = left + a * right; sides take turns."""
    rounds = ", ".join(f"named_struct('m', {m}L, 'o', {(o + seed) % PRIME}L, 'n', {(a, b)[i % 2]}L)" for i, (m, o) in enumerate(zip(MULTIPLIERS, OFFSETS)))
    h = f"(((s.v % {PRIME}L) * p.m + p.o) % {PRIME}L)"
    step = f"named_struct('u', s.v, 'v', (s.u + ({h} * {h} + {h}) % {PRIME}L) % p.n)"
    return f"aggregate(array({rounds}), named_struct('u', {x} % {a}L, 'v', {x} div {a}L), (s, p) -> {step}, s -> s.u + s.v * {a}L)"


def permute(x: str, n: int, seed: int) -> Column:
    """The permuted number of row ``x`` among ``n``, by cycle walking.

    Fewer than ``a`` cells lie outside, so at most ``a`` steps are needed, and 64 all but surely;
    should a walk be longer, the query fails rather than give a wrong place.
    """
    a, b = grid(n)
    again = f"CASE WHEN w < {n}L THEN w ELSE {feistel('w', a, b, seed)} END"
    walked = F.expr(f"aggregate(sequence(1, {min(a, WALKS)}), {feistel(x, a, b, seed)}, (w, i) -> {again})")
    return F.when(walked < n, walked).otherwise(F.raise_error(F.lit("cycle walking did not end")).cast("long"))


def numbered(rows: DataFrame, key: str, ties: list[str], seed: int, bins: int) -> tuple[DataFrame, int]:
    """``rows`` with ``_row``, their global number in the order of the hashed key, and their count."""
    hashed = rows.withColumn("_h", mixed(F.coalesce(F.col(key), F.lit(0).cast("long")), seed))
    hashed = cut(hashed.withColumn("_bin", F.floor(F.col("_h") * F.lit(bins).cast("long") / F.lit(PRIME)).cast("long")))
    # As many rows as there are bins, however large the table is.
    sizes = hashed.groupBy("_bin").count().collect()
    n = sum(r["count"] for r in sizes)
    starts, upto = [], 0
    for r in sorted(sizes, key=lambda r: r["_bin"]):
        starts.append((r["_bin"], upto))
        upto += r["count"]
    starts = rows.sparkSession.createDataFrame(starts, "_bin long, _start long")
    order = Window.partitionBy("_bin").orderBy("_h", F.col(key).asc_nulls_first(), *ties)
    ranked = hashed.withColumn("_at", F.row_number().over(order).cast("long") - 1)
    return ranked.join(F.broadcast(starts), "_bin").withColumn("_row", F.col("_start") + F.col("_at")), n


def shard(docs: DataFrame, shards: int = 8, seed: int = 1, id_col: str = "doc_id", text_col: str = "text", bins: int | None = None) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot and grown_shard of every row."""
    spark = docs.sparkSession
    bins = bins or 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    slim = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        (F.octet_length(text).cast("long") + 1).alias("size"),
        F.crc32(text).alias("text_crc32"),
    )
    rows, n = numbered(slim, "doc_id", ["text_crc32", "size"], seed, bins)
    placed = rows.withColumn("_place", permute("_row", n, seed))
    return placed.select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit("rows").alias("law"),
        (F.col("_place") % shards).cast("int").alias("shard"),
        F.floor(F.col("_place") / shards).cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
    )


def op6_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard(documents(spark, sf_dir))
