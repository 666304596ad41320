"""Near-duplicate documents by ProbMinHash, banding and verification.

Equal texts are folded first.  Each distinct text's five-word shingles, weighted by their number
of occurrences, send arrivals of a Poisson process of their weight's rate to random registers; a
register keeps its earliest arrival.  A shingle stops once its next arrival is later than all
registers', which ends after little more than one arrival per shingle.  Two texts agree in a
register with the probability of their probability Jaccard similarity (the plain Jaccard
similarity where no shingle repeats).  Texts that agree in a whole band are candidates.

Candidates are verified on whole texts, in two rounds.  First every text of a bucket against the
bucket's head, which links groups of copies without listing their pairs.  Then the buckets that
still hold several classes are cut into tiles of bounded rows and bytes, a large class into tiles
of its own, and every two tiles that can hold a pair across classes meet in a task.  Both rounds
look at the registers first and fetch texts only for what is left: a pair whose registers agree in
less than ``least`` of the cases is dropped (a similarity of 0.8 misses 0.62 with a probability
below 1e-5; ``least=0`` verifies every pair that shares a bucket).  A task returns only links that
join classes, so no pair list leaves it, however large a bucket is.  A pair that shares several
buckets is looked at in the first.

Defined cases: a null text is empty; texts without words are near only to equal texts; texts of
fewer than five words are one shingle; rows of one id are one document, whatever texts they hold,
and each of its texts is compared; a text that has no id at all is known by a negative number from
its digest, and equal texts without ids are one document; repeated rows each give a row; an empty
table gives no rows; other columns, whatever their names, are ignored, and kept by ``keep_one``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aggclust.llm.batches import cut, documents, release, slabs
from aggclust.llm.components import components
from aggclust.llm.fingerprints import mix
from aggclust.llm.shingles import shingles

SIMILARITY, ROWS, BANDS = 0.8, 5, 22
SLAB, FEW, TILE, TILE_BYTES, LEAST = 500_000, 500_000, 2048, 8_000_000, 0.62
_ARRIVAL, _TURN = np.uint64(0xD1B54A32D192ED03), np.uint64(0x8CB92BA72F3D8DD7)


def probminhash(owner: np.ndarray, digest: np.ndarray, weight: np.ndarray, sets: int, registers: int) -> np.ndarray:
    """The shingle that reached each register first, (sets, registers); sets without shingles keep zeros."""
    time = np.full(sets * registers, np.inf)
    who = np.zeros(sets * registers, np.uint64)
    clock = np.zeros(len(digest))
    rate = weight.astype(float)
    own, key = owner, digest
    arrival = np.ones(1, np.uint64)
    while len(own):
        h = mix(key + arrival * _ARRIVAL)
        # Uniform in (0, 1], hence a finite exponential waiting time.
        clock = clock - np.log(((h >> np.uint64(11)).astype(float) + 1) / 2.0**53) / rate
        at = own * registers + (mix(h ^ _TURN) % np.uint64(registers)).astype(np.int64)
        early = clock < time[at]
        a, t = at[early], clock[early]
        np.minimum.at(time, a, t)
        won = time[a] == t
        who[a[won]] = key[early][won]
        latest = time.reshape(sets, registers).max(1)
        go = clock < latest[own]
        own, key, clock, rate = own[go], key[go], clock[go], rate[go]
        arrival = arrival + np.uint64(1)
    return who.reshape(sets, registers)


def bands(who: np.ndarray, rows: int, count: int) -> np.ndarray:
    """A key per band of each set."""
    keys = np.zeros((len(who), count), np.uint64)
    for r in range(rows):
        keys = mix(keys + who[:, r : rows * count : rows] + np.uint64(r + 1))
    return mix(keys + np.arange(count, dtype=np.uint64) * _TURN).view(np.int64)


def _sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for lo, hi, part in slabs(batch.column(2), SLAB):
            owner, digest, n = shingles(part)
            keys = bands(probminhash(owner, digest, n, len(part), ROWS * BANDS), ROWS, BANDS)
            some = np.bincount(owner, minlength=len(part)) > 0
            rows = [k.tolist() if s else [] for k, s in zip(keys, some)]
            yield pa.RecordBatch.from_arrays([*(batch.column(c).slice(lo, hi - lo) for c in (0, 1)), pa.array(rows, pa.list_(pa.int64()))], names=["doc_id", "mark", "bands"])


def _register(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """node, text -> node, bytes, and the registers, 32 bits of each."""
    for batch in batches:
        for lo, hi, part in slabs(batch.column(1), SLAB):
            owner, digest, n = shingles(part)
            who = probminhash(owner, digest, n, hi - lo, ROWS * BANDS).astype(np.uint32)
            size = [len(t.encode("utf-8")) for t in part]
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.array(size, pa.int64()), pa.array([w.tobytes() for w in who], pa.binary())], names=["node", "size", "registers"])


def _registers(column: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint32).reshape(len(column), ROWS * BANDS)


def _agreeing(least: float):
    """Pairs (a, b, size, left, right) whose registers agree in ``least`` of the cases."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if len(batch):
                keep = (_registers(batch.column(3)) == _registers(batch.column(4))).mean(1) >= least
                yield pa.RecordBatch.from_arrays([batch.column(c).filter(pa.array(keep)) for c in range(3)], names=["a", "b", "size"])

    return run


def probability_jaccard(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Of two sorted (digests, weights): sum over common d of 1 / sum over e of max(a_e / a_d, b_e / b_d)."""
    (ka, wa), (kb, wb) = a, b
    common, ia, ib = np.intersect1d(ka, kb, assume_unique=True, return_indices=True)
    if not len(common):
        return 0.0
    # With rho = b_d / a_d, the inner sum is (sum of a over ratios <= rho + sum of b over others / rho) / a_d.
    ratio = wb[ib] / wa[ia]
    steps, where = np.unique(ratio, return_inverse=True)
    a_at = np.bincount(where, weights=wa[ia], minlength=len(steps))
    b_at = np.bincount(where, weights=wb[ib], minlength=len(steps))
    a_low = wa.sum() - wa[ia].sum() + 0.0  # shingles of a alone have ratio 0
    b_high = wb.sum() - wb[ib].sum() + 0.0  # those of b alone have ratio infinity
    low = np.cumsum(a_at) + a_low
    high = b_high + b_at.sum() - np.cumsum(b_at)
    inner = (low + high / steps)[where] / wa[ia]
    return float((1 / inner).sum())


def _sets(texts: list[str]) -> list[tuple[np.ndarray, np.ndarray]]:
    owner, digest, n = shingles(texts)
    bound = np.searchsorted(owner, np.arange(len(texts) + 1))
    return [(digest[s:e], n[s:e].astype(float)) for s, e in zip(bound, bound[1:])]


def _links(found: list[tuple]) -> pa.RecordBatch:
    a, b, near = zip(*found) if found else ((), (), ())
    return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(near, pa.float64())], names=["a", "b", "similarity"])


def _stars(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links of heads; rows (head, part, side, node, text) come sorted, a head's own text first."""
    name, head = None, None
    for batch in batches:
        heads, parts, sides, nodes = (batch.column(c).to_pylist() for c in range(4))
        for lo, hi, texts in slabs(batch.column(4), SLAB):
            found = []
            for k, own in zip(range(lo, hi), _sets(texts)):
                if sides[k] == 0:
                    name, head = (heads[k], parts[k]), own
                elif name == (heads[k], parts[k]):
                    near = probability_jaccard(head, own)
                    if near >= SIMILARITY - 1e-9:
                        found.append((min(heads[k], nodes[k]), max(heads[k], nodes[k]), near))
            yield _links(found)


def _blocks(batches: Iterator[pa.RecordBatch], columns: int) -> Iterator[pa.Table]:
    """The rows of each block, from batches sorted by their first ``columns`` columns."""
    held: list[pa.RecordBatch] = []
    at = None
    for batch in batches:
        if not len(batch):
            continue
        keys = [batch.column(c) for c in range(columns)]
        rows = list(zip(*(k.to_pylist() for k in keys)))
        begin = 0
        for i in range(len(rows) + 1):
            if i == len(rows) or rows[i] != at:
                if i > begin:
                    held.append(batch.slice(begin, i - begin))
                if i < len(rows):
                    if held:
                        yield pa.Table.from_batches(held).combine_chunks()
                    held, at, begin = [], rows[i], i
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def _candidates(table: pa.Table, least: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows (x, y) of a block to be verified and the share of agreeing registers.

    They are of two classes, on the two sides of the block, and share no earlier bucket.
    """
    side, band = table["side"].to_numpy(), table["band"][0].as_py()
    who = _registers(table["registers"].combine_chunks())
    part = table["component"].to_numpy()
    left = np.flatnonzero(side == 0)
    same = table["alone"][0].as_py()
    right = left if same else np.flatnonzero(side == 1)
    found = []
    wide = max(1, 2_000_000 // max(1, len(right) * who.shape[1]))
    for at in range(0, len(left), wide):
        rows = left[at : at + wide]
        equal = who[rows][:, None, :] == who[right][None, :, :]
        est = equal.mean(2)
        x, y = np.nonzero((est >= least) & (part[rows][:, None] != part[right][None, :]))
        if same:
            up = rows[x] < right[y]
            x, y = x[up], y[up]
        if len(x):
            first = equal[x, y].reshape(len(x), BANDS, ROWS).all(2).argmax(1) == band
            found.append((rows[x[first]], right[y[first]], est[x[first], y[first]]))
    return tuple(np.concatenate(c) for c in zip(*found)) if found else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))


BLOCK = "key long, lo_class long, lo_tile int, hi_class long, hi_tile int, alone boolean, band int, side int, node long, component long, registers binary"
_BLOCK = [c.split(" ")[0] for c in BLOCK.split(", ")]


def _surviving(least: float):
    """The rows of each block that have a candidate in it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _blocks(batches, 5):
            x, y, _ = _candidates(table, least)
            if len(x):
                yield from table.take(pa.array(np.unique(np.concatenate([x, y])))).combine_chunks().to_batches()

    return run


def _joining(least: float):
    """Links that join classes, among the rows and texts of each block; the nearest are verified first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _blocks(batches, 5):
            x, y, est = _candidates(table, least)
            if not len(x):
                continue
            node = table["node"].to_numpy()
            _, part = np.unique(table["component"].to_numpy(), return_inverse=True)
            order = np.argsort(-est, kind="stable")
            used = np.unique(np.concatenate([x, y]))
            sets = dict(zip(used.tolist(), _sets(table["text"].take(pa.array(used)).to_pylist())))
            root = list(range(int(part.max()) + 1))

            def top(c: int) -> int:
                while root[c] != c:
                    root[c] = root[root[c]]
                    c = root[c]
                return c

            found = []
            for p, q in zip(x[order].tolist(), y[order].tolist()):
                a, b = top(part[p]), top(part[q])
                if a != b:
                    near = probability_jaccard(sets[p], sets[q])
                    if near >= SIMILARITY - 1e-9:
                        root[max(a, b)] = min(a, b)
                        found.append((min(node[p], node[q]), max(node[p], node[q]), near))
            yield _links(found)

    return run


def _few(df: DataFrame) -> DataFrame:
    """A broadcast of at most ``FEW`` ids and digests (30 MB); beyond that the join shuffles."""
    return F.broadcast(df) if df.count() <= FEW else df


def nameless(mark="mark"):
    return -F.shiftrightunsigned(F.xxhash64(mark), 1) - 1


def digest(text_col: str = "text"):
    return F.unhex(F.md5(F.coalesce(F.col(text_col).cast("string"), F.lit(""))))


def _named(marked: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """mark, node, id, bands of every distinct text, and links between the texts of one id, if there are such.

    A node is the smallest id of its text; where an id is the smallest of several texts, the first
    digest has it and the others are known by their digests.
    """
    named = marked.groupBy("mark").agg(F.min("doc_id").alias("id"), F.first("bands").alias("bands"))
    several = marked.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.min("mark").alias("lo"), F.max("mark").alias("hi")).where("lo < hi")
    several = cut(several.select("doc_id"))
    if several.isEmpty():
        return cut(named.select("mark", F.coalesce("id", nameless()).alias("node"), "id", "bands")), None
    shared = named.join(_few(several), F.col("id") == F.col("doc_id"), "left_semi").groupBy("id").agg(F.min("mark").alias("first"))
    shared = cut(shared.withColumnRenamed("id", "_id"))
    own = F.when(F.coalesce(F.col("mark") == F.col("first"), F.lit(True)), F.col("id"))
    nodes = cut(named.join(_few(shared), F.col("id") == F.col("_id"), "left").select("mark", F.coalesce(own, nameless()).alias("node"), "id", "bands"))
    held = marked.join(_few(several), "doc_id", "left_semi").join(nodes.select("mark", "node"), "mark").select("doc_id", "node").distinct()
    least = held.groupBy("doc_id").agg(F.min("node").alias("a"))
    return nodes, cut(least.join(held, "doc_id").where("node > a").select("a", F.col("node").alias("b")))


def groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: float = LEAST) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Rows (doc_id, mark), a class per distinct text (mark, node, class_id), and the verified links (a, b, similarity) of nodes."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), digest(text_col).alias("mark"), text.alias("text"))
    marked = cut(rows.mapInArrow(_sketch, "doc_id long, mark binary, bands array<long>"))
    nodes, same = _named(marked)
    filed = nodes.select("node", F.posexplode("bands").alias("band", "key"))
    heads = filed.groupBy("key").agg(F.min("node").alias("head"), F.max("node").alias("tail")).where("head < tail")
    shared = cut(filed.join(heads.select("key", "head"), "key"))
    wanted = _few(cut(nodes.join(shared.select("node").distinct(), "node", "left_semi").select("node", F.col("mark").alias("_mark"))))
    # A text is read from the rows that gave it its name.
    own = rows.select(F.coalesce("doc_id", nameless()).alias("node"), "mark", "text")
    if same is not None:
        own = own.unionByName(rows.where("doc_id IS NOT NULL").select(nameless().alias("node"), "mark", "text"))
    own = own.join(wanted, "node").where("mark = _mark")
    texts = cut(own.groupBy("node").agg(F.first("text").alias("text")))
    registers = cut(texts.mapInArrow(_register, "node long, size long, registers binary"))
    del filed, heads, own, wanted
    release(docs.sparkSession)

    stars = shared.where("node > head").select(F.col("head").alias("a"), F.col("node").alias("b")).distinct()
    left = registers.select(F.col("node").alias("a"), F.col("registers").alias("left"))
    right = registers.select(F.col("node").alias("b"), "size", F.col("registers").alias("right"))
    likely = cut(stars.join(left, "a").join(right, "b").select("a", "b", "size", "left", "right").mapInArrow(_agreeing(least), "a long, b long, size long"))
    parts = likely.groupBy("a").agg(F.ceil(F.sum("size") / TILE_BYTES).cast("int").alias("parts"))
    likely = likely.join(parts, "a").select("a", "b", F.pmod(F.xxhash64("b"), F.greatest("parts", F.lit(1))).cast("int").alias("part"))
    ends = likely.select("a", "part", F.lit(0).alias("side"), F.col("a").alias("node")).distinct().unionByName(likely.select("a", "part", F.lit(1).alias("side"), F.col("b").alias("node")))
    ends = ends.join(texts, "node").select("a", "part", "side", "node", "text").repartition("a", "part").sortWithinPartitions("a", "part", "side", "node")
    links = cut(ends.mapInArrow(_stars, "a long, b long, similarity double"))

    del stars, left, right, likely, parts, ends
    release(docs.sparkSession)
    placed = cut(shared.select("key", "band", "node").join(_classes(links, same), "node", "left").withColumn("component", F.coalesce("component", "node")))
    dealt = _tile_pairs(placed, registers).join(registers.select("node", "registers"), "node").select(*_BLOCK)
    order = _BLOCK[:5]
    release(docs.sparkSession)
    left = cut(dealt.repartition(*order).sortWithinPartitions(*order, "side", "node").mapInArrow(_surviving(least), BLOCK))
    last = left.join(texts, "node").select(*_BLOCK, "text").repartition(*order).sortWithinPartitions(*order, "side", "node")
    links = links.unionByName(cut(last.mapInArrow(_joining(least), "a long, b long, similarity double")))
    known = nodes.join(_classes(links, same), "node", "left").select("mark", "node", "id", F.coalesce("component", "node").alias("component"))
    known = cut(known)
    # A class is named by its smallest id; only where a text is known by its digest can that differ from the smallest node.
    names = cut(known.where("component < 0 AND id IS NOT NULL").groupBy("component").agg(F.min("id").alias("_name")))
    known = known.join(_few(names), "component", "left").withColumn("class_id", F.coalesce("_name", "component"))
    return marked.select("doc_id", "mark"), cut(known.select("mark", "node", "class_id")), links


def _classes(links: DataFrame, same: DataFrame | None) -> DataFrame:
    pairs = links.select("a", "b")
    return components(pairs if same is None else pairs.unionByName(same))


def _tile_pairs(placed: DataFrame, registers: DataFrame) -> DataFrame:
    """The rows of buckets with several classes, once for each two tiles that may hold a pair across classes.

    Classes beyond a tile's rows or bytes get tiles of their own, which never meet each other;
    the smaller classes of a bucket share tiles, each class in one.
    """
    mixed = placed.groupBy("key").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo < hi").select("key")
    rows = cut(placed.join(mixed, "key", "left_semi").join(registers.select("node", "size"), "node"))
    per = rows.groupBy("key", "component").agg(F.count("*").alias("rows"), F.sum("size").alias("bytes"))
    per = per.withColumn("need", F.greatest(F.col("rows") / TILE, F.col("bytes") / TILE_BYTES))
    small = F.when(F.col("need") <= 1, F.col("need"))
    rest = per.groupBy("key").agg(F.ceil(F.sum(small)).cast("int").alias("shared"))
    per = per.join(rest, "key").select("key", "component", F.when(F.col("need") > 1, F.col("component")).alias("class"), F.when(F.col("need") > 1, F.ceil("need").cast("int")).otherwise(F.greatest("shared", F.lit(1))).alias("tiles"))
    per = cut(per)
    big = per.where("class IS NOT NULL")
    tiles = big.select("key", "class", "tiles").unionByName(per.where("class IS NULL").select("key", "class", "tiles").distinct())
    tiles = tiles.select("key", "class", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)).alias("tile")).select("key", F.struct("class", "tile").alias("t"))
    other = tiles.select("key", F.col("t").alias("u"))
    pairs = tiles.join(other, "key").where("t <= u AND (t.class IS NULL OR NOT t.class <=> u.class)")
    pairs = pairs.select("key", "t", "u", F.col("t").eqNullSafe(F.col("u")).alias("alone"))
    deal = F.when(F.col("class").isNull(), F.pmod(F.xxhash64("component"), "tiles")).otherwise(F.pmod(F.xxhash64("node"), "tiles")).cast("int")
    at = rows.join(per, ["key", "component"]).select("key", "band", "node", "component", F.struct(F.col("class"), deal.alias("tile")).alias("own"))
    sides = pairs.select("key", "t", "u", "alone", F.col("t").alias("own"), F.lit(0).alias("side")).unionByName(pairs.where("NOT alone").select("key", "t", "u", "alone", F.col("u").alias("own"), F.lit(1).alias("side")))
    sides = sides.withColumns({"_class": F.col("own.class"), "_tile": F.col("own.tile")}).drop("own")
    at = at.select("key", "band", "node", "component", F.col("own.class").alias("_class"), F.col("own.tile").alias("_tile"))
    none = F.lit(-(2**63))
    met = at.withColumn("_class", F.coalesce("_class", none)).join(sides.withColumn("_class", F.coalesce("_class", none)), ["key", "_class", "_tile"])
    return met.select("key", F.col("t.class").alias("lo_class"), F.col("t.tile").alias("lo_tile"), F.col("u.class").alias("hi_class"), F.col("u.tile").alias("hi_tile"), "alone", "band", "side", "node", "component")


def classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: float = LEAST) -> tuple[DataFrame, DataFrame]:
    """doc_id and class_id of every row, and the verified links."""
    rows, by_mark, links = groups(docs, id_col, text_col, least)
    return rows.join(by_mark, "mark").select("doc_id", "class_id"), links


def keep_one(docs: DataFrame, least: float = LEAST) -> DataFrame:
    """One row of each class, all columns: a text of the class's smallest id, one of repeated rows."""
    rows, by_mark, _ = groups(docs, least=least)
    held = rows.join(by_mark, "mark").where(F.coalesce("doc_id", "node") == F.col("class_id"))
    chosen = cut(held.groupBy(F.col("class_id").alias("_node")).agg(F.min("mark").alias("_mark")))
    marked = docs.select(F.struct("*").alias("_row"), digest().alias("_own"), F.coalesce(F.col("doc_id").cast("long"), nameless(digest())).alias("_node"))
    kept = marked.join(_few(chosen), "_node").where("_own = _mark").dropDuplicates(["_node"])
    return kept.select(*(F.col("_row").getField(c).alias(c) for c in docs.columns))


def op4_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, class_id (the smallest id of the class) and kept."""
    found, _ = classes(documents(spark, sf_dir))
    return found.select("doc_id", "class_id", F.coalesce(F.col("doc_id") == F.col("class_id"), F.lit(False)).alias("kept"))
