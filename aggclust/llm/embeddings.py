"""Near-duplicate embeddings by int8 tile products with rigorous error bounds.

Equal vectors of a label are first folded into one with a count, so copies cost nothing.  Each
label's distinct vectors are dealt into tiles by hash, and a task gets one pair of tiles.  A label
has ``SIDES`` tiles until they hold ``LARGEST`` numbers each, so a vector is sent to no more than
``SIDES`` tasks before that, and to as few as its memory allows beyond.  There the unit vectors are
quantised to int8 with a scale of their own; a product of the codes misses the cosine by at most
|u'| e_w + e_u |w'| + e_u e_w, where u', w' are the dequantised vectors and e their quantisation
errors' norms, so only pairs whose product plus bound reaches the threshold are computed again in
double precision.  Products are taken stripe by stripe, and links are folded into degrees and
components as they are found: a task holds neither its matrix nor its links, and returns, per
vector that has links, the number of vectors linked and the smallest vector of its part of the
graph.

Defined cases: vectors that are null or empty, have null or non-finite components or norm zero,
or have no label link with nothing and are their own component; vectors of different lengths do
not link; rows that repeat an id are vectors of their own; repeated rows count as vectors of their own; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aggclust.llm.batches import cut
from aggclust.llm.components import components

THRESHOLD, TILE, SIDES, LARGEST = 0.93, 4096, 16, 2_000_000
#: Products and pairs that a task holds at a time.
PRODUCTS, PAIRS = 2_000_000, 200_000


def quantise(unit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """int8 codes, scales, error norms (rounded up) and norms of the dequantised vectors."""
    scale = np.abs(unit).max(1) / 127
    codes = np.rint(unit / scale[:, None]).astype(np.int8)
    back = codes * scale[:, None]
    slack = 1 + 1e-9
    return codes, scale, np.linalg.norm(unit - back, axis=1) * slack + 1e-12, np.linalg.norm(back, axis=1) * slack


def linked_pairs(a: np.ndarray, b: np.ndarray, threshold: float, same: bool):
    """Index pairs (i, j) of rows of ``a`` and ``b`` with cosine >= threshold; i < j if ``same``. In stripes."""
    na, nb = np.linalg.norm(a, axis=1), np.linalg.norm(b, axis=1)
    ca, sa, ea, ma = quantise(a / na[:, None])
    cb, sb, eb, mb = quantise(b / nb[:, None])
    # BLAS multiplies the codes as floats; sums of products of codes are exact in them.
    exact = np.float32 if a.shape[1] <= 1024 else np.float64
    fa, fb = ca.astype(exact), cb.astype(exact).T
    stripe = max(1, PRODUCTS // max(1, len(b)))
    for lo in range(0, len(a), stripe):
        rows = slice(lo, lo + stripe)
        product = (fa[rows] @ fb) * sa[rows, None] * sb[None, :]
        bound = ma[rows, None] * eb[None, :] + ea[rows, None] * mb[None, :] + ea[rows, None] * eb[None, :]
        i, j = np.nonzero(product + bound + 1e-5 >= threshold)
        if same:
            up = j > i + lo
            i, j = i[up], j[up]
        for at in range(0, len(i), PAIRS):
            x, y = i[at : at + PAIRS] + lo, j[at : at + PAIRS]
            cosine = np.einsum("ij,ij->i", a[x], b[y]) / (na[x] * nb[y])
            hit = cosine >= threshold
            if hit.any():
                yield x[hit], y[hit]


def _fold(root: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """``root`` (the smallest position of each one's component) after links between ``x`` and ``y``."""
    a, b = np.minimum(root[x], root[y]), np.maximum(root[x], root[y])
    open_ = a < b
    if not open_.any():
        return root
    edges = np.unique(a[open_] * len(root) + b[open_])
    a, b = edges // len(root), edges % len(root)
    to = np.arange(len(root))
    while True:
        low = np.minimum(to[a], to[b])
        before = to.copy()
        np.minimum.at(to, a, low)
        np.minimum.at(to, b, low)
        to = to[to]
        if (to == before).all():
            return to[root]


def _tile_pair(threshold: float):
    def work(table: pa.Table) -> pa.Table:
        # In the order of the ids, the smallest position of a component is its smallest id.
        table = table.sort_by("_rep").combine_chunks()
        vectors = table["_v"].combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(table), -1)
        ids, counts = table["_node"].to_numpy(), table["_n"].to_numpy()
        left = table["_side"].to_numpy() == 0
        same = bool(table["_i"][0].as_py() == table["_j"][0].as_py())
        first = np.flatnonzero(left)
        second = first if same else np.flatnonzero(~left)
        links, root = np.zeros(len(ids), np.int64), np.arange(len(ids))
        if len(first) and len(second):
            for x, y in linked_pairs(vectors[first], vectors[second], threshold, same):
                x, y = first[x], second[y]
                np.add.at(links, x, counts[y])
                np.add.at(links, y, counts[x])
                root = _fold(root, x, y)
        has = links > 0
        return pa.table({"node": pa.array(ids[has], pa.int64()), "links": pa.array(links[has], pa.int64()), "root": pa.array(ids[root[has]], pa.int64())})

    return work


def near_duplicates(
    vectors: DataFrame,
    threshold: float = THRESHOLD,
    id_col: str = "vec_id",
    vector_col: str = "embedding",
    label_col: str = "label",
    tile: int | None = None,
) -> DataFrame:
    """vec_id, n_links, component_id and kept of every row; ``tile`` fixes the vectors of a tile."""
    # Floats travel as they are; all arithmetic is in double precision.
    narrow = vectors.schema[vector_col].dataType.simpleString() == "array<float>"
    v = F.col(vector_col) if narrow else F.col(vector_col).cast("array<double>")
    bad = F.exists(F.col("_v"), lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    zero = ~F.exists(F.col("_v"), lambda x: x != 0)
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(label_col).cast("string").alias("_label"), v.alias("_v"))
    fit = F.coalesce(F.col("_label").isNotNull() & F.col("_v").isNotNull() & (F.size("_v") > 0) & ~F.coalesce(bad, F.lit(True)) & ~zero, F.lit(False))
    rows = rows.withColumn("_fit", fit & F.col("vec_id").isNotNull())
    keyed = rows.withColumns({"_h": F.xxhash64("_v"), "_g": F.xxhash64(F.lit(1), F.reverse("_v")), "_d": F.size("_v")})
    key = ["_label", "_d", "_h", "_g"]
    reps = cut(keyed.where("_fit").groupBy(*key).agg(F.min("vec_id").alias("_rep"), F.count("*").alias("_n"), F.first("_v").alias("_v")))
    # A vector is known by its smallest id; where ids hold several vectors, by a number from its hash.
    several = cut(reps.groupBy("_rep").agg(F.count("*").alias("_c")).where("_c > 1").select("_rep"))
    unique = several.isEmpty()
    if unique:
        reps = reps.withColumn("_node", F.col("_rep"))
    else:
        shared = several.withColumn("_shared", F.lit(True))
        hashed = -F.shiftrightunsigned(F.xxhash64("_label", "_h", "_g"), 1) - 1
        reps = cut(reps.join(shared, "_rep", "left").withColumn("_node", F.when(F.col("_shared"), hashed).otherwise(F.col("_rep"))).drop("_shared"))
    most = F.greatest(F.lit(1.0), F.least(F.greatest(F.col("_all") / SIDES, F.lit(float(TILE))), LARGEST / F.col("_d")))
    tiles = F.ceil(F.col("_all") / (most if tile is None else F.lit(tile))).cast("int")
    per = reps.groupBy("_label", "_d").agg(F.count("*").alias("_all"))
    dealt = reps.join(per, ["_label", "_d"]).select("_label", "_d", "_rep", "_node", "_n", "_v", tiles.alias("_t"))
    dealt = dealt.withColumn("_own", F.pmod(F.xxhash64("_node"), F.col("_t")).cast("int"))
    dealt = dealt.withColumn("_other", F.explode(F.sequence(F.lit(0), F.col("_t") - 1)))
    dealt = dealt.select(
        "_label", "_d", "_rep", "_node", "_n", "_v", F.least("_own", "_other").alias("_i"), F.greatest("_own", "_other").alias("_j"), (F.col("_own") > F.col("_other")).cast("int").alias("_side")
    )
    found = cut(dealt.groupBy("_label", "_d", "_i", "_j").applyInArrow(_tile_pair(threshold), "node long, links long, root long"))
    degree = found.groupBy(F.col("node").alias("_node")).agg(F.sum("links").alias("_links"))
    classes = components(found.select(F.col("node").alias("a"), F.col("root").alias("b"))).withColumnRenamed("node", "_node")
    known = reps.drop("_v").join(degree, "_node", "left").join(classes, "_node", "left")
    if not unique:
        known = cut(known.withColumn("_part", F.coalesce("component", "_node")).drop("component"))
        known = known.join(known.groupBy("_part").agg(F.min("_rep").alias("component")), "_part").drop("_part")
    out = keyed.drop("_v").join(known.withColumn("_fit", F.lit(True)), [*key, "_fit"], "left")
    component = F.when(F.col("_fit"), F.coalesce("component", "_rep")).otherwise(F.col("vec_id"))
    out = out.select("vec_id", F.when(F.col("_fit"), F.col("_n") - 1 + F.coalesce("_links", F.lit(0))).otherwise(0).cast("long").alias("n_links"), component.alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def op2_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))


def oracle() -> str:
    """All pairs, and the components by repeated minima (the smallest member reaches all in few steps)."""
    return f"""
WITH RECURSIVE v AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
ok AS (SELECT vec_id, label, e, sqrt(list_sum(list_transform(e, lambda x: x * x))) AS n FROM v
    WHERE label IS NOT NULL AND e IS NOT NULL AND len(e) > 0 AND len(list_filter(e, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0),
link AS (SELECT a.vec_id AS u, b.vec_id AS w FROM ok a JOIN ok b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.e) = len(b.e)
    WHERE a.n > 0 AND b.n > 0 AND list_inner_product(a.e, b.e) / (a.n * b.n) >= {THRESHOLD}),
reach AS (SELECT u AS s, w AS t FROM link UNION SELECT s, link.w FROM reach JOIN link ON reach.t = link.u)
SELECT v.vec_id, CAST(coalesce((SELECT count(*) FROM link WHERE u = v.vec_id), 0) AS BIGINT) AS n_links,
    least(v.vec_id, coalesce((SELECT min(t) FROM reach WHERE s = v.vec_id), v.vec_id)) AS component_id,
    v.vec_id = least(v.vec_id, coalesce((SELECT min(t) FROM reach WHERE s = v.vec_id), v.vec_id)) AS kept
FROM v"""
