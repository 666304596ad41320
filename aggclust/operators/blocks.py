"""Every pair of rows, in blocks: tiles of rows meet two by two, each block in NumPy.

A tile is one row that holds many, so what is shuffled is a row per block side, not a row per pair.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

TILE, CHUNK = 4096, 512
#: Pairs whose distance is taken again from differences, at a time.
AGAIN = 65_536


def block_pairs(rows: DataFrame, key: str, vec: str, work: Callable, schema: str, tile: int = TILE) -> DataFrame:
    """``work(keys, x, keys, y, same)`` on each two tiles and on each tile with itself (``same``).

    It gives the columns of ``schema`` for one block.  Rows without a key or a coordinate are left out.
    """
    rows = rows.select(F.col(key).alias("k"), F.col(vec).alias("v")).where("k IS NOT NULL AND v IS NOT NULL AND NOT exists(v, c -> c IS NULL)")
    tiles = max(1, -(-rows.count() // tile))
    dealt = rows.groupBy(F.pmod(F.xxhash64("k", "v"), F.lit(tiles)).cast("int").alias("t")).agg(F.collect_list(F.struct("k", "v")).alias("rows"))
    pairs = F.transform(F.sequence(F.lit(0), F.lit(tiles - 1)), lambda o: F.struct(F.least("t", o).alias("lo"), F.greatest("t", o).alias("hi")))
    sides = dealt.select(F.explode(pairs).alias("p"), "t", "rows").select("p.lo", "p.hi", "t", "rows")
    typed = pa.schema([(p.split()[0], {"string": pa.string(), "long": pa.int64(), "double": pa.float64()}[p.split()[1]]) for p in schema.split(", ")])

    def run(table: pa.Table) -> pa.Table:
        lo, hi = table["lo"][0].as_py(), table["hi"][0].as_py()
        found = {t: _tile(cell.values) for t, cell in zip(table["t"].to_pylist(), table["rows"])}
        # A tile that no row was dealt to has no blocks.
        if len(found) < (1 if lo == hi else 2):
            return typed.empty_table()
        (ka, x), (kb, y) = found[lo], found[hi]
        return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(work(ka, x, kb, y, lo == hi), typed)], schema=typed)

    return sides.groupBy("lo", "hi").applyInArrow(run, schema)


def _tile(cells: pa.StructArray) -> tuple[np.ndarray, np.ndarray]:
    keys, flat = (cells.field(i) for i in range(2))
    k = keys.to_numpy(zero_copy_only=False)
    return k, flat.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(k), -1)


def _differences(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Squared distances of every two rows, summed coordinate by coordinate."""
    out = np.zeros((len(x), len(y)))
    for i in range(x.shape[1]):
        gap = x[:, i, None] - y[None, :, i]
        gap *= gap
        out += gap
    return out


def group_linkage(points: DataFrame, group: str, vec: str, name: str, squared: bool = False) -> DataFrame:
    """a < b and the smallest (``single``), largest (``complete``) or mean (``upgma``) distance of two groups' points."""
    fold = {"single": np.minimum, "complete": np.maximum, "upgma": np.add}[name]

    def work(ka, x, kb, y, same):
        # Sorted by group, each two groups are a rectangle of the block.
        oa, ob = np.argsort(ka, kind="stable"), np.argsort(kb, kind="stable")
        (ga, sa, na), (gb, sb, nb) = (np.unique(k[o], return_index=True, return_counts=True) for k, o in ((ka, oa), (kb, ob)))
        x, y, starts = x[oa], y[ob], {}
        for r, g in enumerate(ga):
            best = None
            for s in range(sa[r], sa[r] + na[r], CHUNK):
                d = _differences(x[s : min(s + CHUNK, sa[r] + na[r])], y)
                d = d if squared else np.sqrt(d, out=d)
                part = fold.reduceat(fold.reduce(d, axis=0), sb)
                best = part if best is None else fold(best, part)
            starts[r] = best
        out = [(min(g, h), max(g, h), starts[r][c], int(na[r] * nb[c])) for r, g in enumerate(ga) for c, h in enumerate(gb) if (g < h if same else g != h)]
        return list(zip(*out)) or [()] * 4

    kind = points.schema[group].dataType.simpleString()
    wide = kind if kind == "string" else "long"
    parts = block_pairs(points.withColumn(group, F.col(group).cast(wide)), group, vec, work, f"a {wide}, b {wide}, v double, pairs long")
    whole = {"single": F.min("v"), "complete": F.max("v"), "upgma": F.sum("v") / F.sum("pairs")}[name]
    return parts.groupBy("a", "b").agg(whole.alias("d")).select(F.col("a").cast(kind), F.col("b").cast(kind), "d")


def _strips(x: np.ndarray, y: np.ndarray, same: bool) -> Iterator[tuple[int, np.ndarray, float]]:
    """First row, squared distances by products, and a bound of their error; a row with itself is infinite."""
    xx, yy = (x * x).sum(1), (y * y).sum(1)
    slack = 8 * (x.shape[1] + 4) * np.finfo(float).eps * (xx.max() + yy.max())
    for s in range(0, len(x), CHUNK):
        d = xx[s : s + CHUNK, None] + yy[None, :]
        d -= 2 * (x[s : s + CHUNK] @ y.T)
        if same:
            r = np.arange(len(d))
            d[r, s + r] = np.inf
        yield s, d, slack


def _exact(x: np.ndarray, y: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    out = np.empty(len(i))
    for s in range(0, len(i), AGAIN):
        p = slice(s, s + AGAIN)
        gap = x[i[p]] - y[j[p]]
        out[p] = np.sqrt((gap * gap).cumsum(1)[:, -1])
    return out


def nearest(rows: DataFrame, key: str, vec: str, k: int) -> DataFrame:
    """u, v, d, rank: the ``k`` rows nearest to each row, ties by the smaller key."""

    def best(ka, x, kb, y, same):
        out = []
        for s, d, slack in _strips(x, y, same):
            top = min(k, d.shape[1] - same)
            if top < 1:
                continue
            # The products only propose: whatever their error could hide is taken again.
            i, j = np.nonzero(d <= np.partition(d, top - 1, axis=1)[:, top - 1 : top] + 2 * slack)
            e = _exact(x, y, i + s, j)
            o = np.lexsort((kb[j], e, i))
            i, j, e = i[o], j[o], e[o]
            keep = np.arange(len(i)) - np.searchsorted(i, i) < top
            out.append((ka[i[keep] + s], kb[j[keep]], e[keep]))
        return out

    def work(ka, x, kb, y, same):
        out = best(ka, x, kb, y, same) + ([] if same else best(kb, y, ka, x, False))
        return [np.concatenate(c) for c in zip(*out)] or [()] * 3

    parts = block_pairs(rows, key, vec, work, "u long, v long, d double")
    # A row's candidates are at most k from each tile.
    near = parts.groupBy("u").agg(F.slice(F.array_sort(F.collect_list(F.struct("d", "v"))), 1, k).alias("near"))
    return near.select("u", F.posexplode("near").alias("p", "x")).select("u", "x.v", "x.d", (F.col("p") + 1).alias("rank"))


def closest(rows: DataFrame, key: str, vec: str, k: int) -> DataFrame:
    """i < j and d of the ``k`` closest pairs, ties by i and j."""

    def work(ka, x, kb, y, same):
        i, j, e = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        for s, d, slack in _strips(x, y, same):
            # Inside a tile each pair is in the strip of the smaller row only.
            if same:
                d[np.arange(d.shape[1])[None, :] < (s + np.arange(len(d)))[:, None]] = np.inf
            limit = np.partition(d, min(k, d.size) - 1, axis=None)[min(k, d.size) - 1]
            limit = limit if np.isfinite(limit) else np.finfo(float).max
            p, q = np.nonzero(d <= min(limit + 2 * slack, e[k - 1] ** 2 + 2 * slack if len(e) >= k else np.inf))
            a, b = ka[p + s], kb[q]
            i, j, e = np.concatenate((i, np.minimum(a, b))), np.concatenate((j, np.maximum(a, b))), np.concatenate((e, _exact(x, y, p + s, q)))
            o = np.lexsort((j, i, e))[:k]
            i, j, e = i[o], j[o], e[o]
        return i, j, e

    return block_pairs(rows, key, vec, work, "i long, j long, d double").orderBy("d", "i", "j").limit(k)


def spread(rows: DataFrame, key: str, vec: str) -> DataFrame:
    """pairs, low, mean: number, least and mean of the distances of all pairs."""

    def work(ka, x, kb, y, same):
        pairs, total, low = 0, 0.0, np.inf
        for s, d, slack in _strips(x, y, same):
            keep = np.arange(d.shape[1])[None, :] > (s + np.arange(len(d)))[:, None] if same else np.ones(d.shape, bool)
            if not keep.any():
                continue
            d[~keep] = np.inf
            p, q = np.unravel_index(np.argmin(d), d.shape)
            near = np.nonzero(d <= d[p, q] + 2 * slack)
            low = min(low, _exact(x, y, near[0] + s, near[1]).min())
            pairs += int(keep.sum())
            total += float(np.sqrt(np.maximum(d[keep], 0)).sum())
        return ([pairs], [low], [total]) if pairs else ([], [], [])

    parts = block_pairs(rows, key, vec, work, "pairs long, low double, total double")
    return parts.agg(F.coalesce(F.sum("pairs"), F.lit(0)).alias("pairs"), F.min("low").alias("low"), (F.sum("total") / F.sum("pairs")).alias("mean"))
