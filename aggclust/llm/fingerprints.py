"""Document fingerprints: invertible Bloom lookup sketches of paragraph digests.

A text's paragraphs are its lines, cut further after about ``RUN`` words where a word's hash says
so, so that an edit changes only the paragraphs it touches.  Each distinct paragraph digest is
added to three cells (count, digest sum, check sum).  Two versions' cells are subtracted; peeling
cells that hold one digest recovers the digests that differ, on either side.  If peeling stops
early, both are sketched again with four times the cells, until it succeeds.  The likeness of two
versions is the share of common digests in all their digests.

A fingerprint is the sketch of ``CELLS`` cells itself, in full: two stored fingerprints subtract
and peel without their texts (``compare``), and the likeness of two rows is taken from their
fingerprints' cells, which are sketched anew, larger, only where these do not suffice.

All texts of a slab are cut, hashed, sketched and peeled together in arrays.

Defined cases: a null text is empty; a text without words has no paragraphs, and two such texts
have likeness 1; equal texts have equal fingerprints; repeated ids follow each other in the order
of their texts' hashes; a null id comes last; the only row is its own next document; very long
texts form a slab of their own; an empty table gives no rows.
"""

from __future__ import annotations

from base64 import b64decode, b64encode
from collections.abc import Iterator
from hashlib import sha256

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aggclust.llm.batches import SLAB, documents, per_document, plan_bytes, slabs

CELLS, GROW, RUN = 24, 4, 4
#: Bytes of text aimed at in a bin, and the most bins: a task streams its bin in slabs, whatever its size.
BIN_BYTES, MOST_BINS = 64_000_000, 16_384
CELL = np.dtype([("count", "<i4"), ("keys", "<u8"), ("checks", "<u8")])
# An odd base of the polynomial hash, finaliser multipliers, and seeds of the cells.
BASE = np.uint64(0x9E3779B97F4A7C15)
FINAL = (np.uint64(0xFF51AFD7ED558CCD), np.uint64(0xC4CEB9FE1A85EC53))
SEEDS = (np.uint64(0x243F6A8885A308D3), np.uint64(0x13198A2E03707344), np.uint64(0xA4093822299F31D0))
CHECK = np.uint64(0x082EFA98EC4E6C89)

_powers: dict[str, np.ndarray] = {}


def mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(33))
    x = x * FINAL[0]
    x = x ^ (x >> np.uint64(33))
    x = x * FINAL[1]
    return x ^ (x >> np.uint64(33))


BYTE = mix(np.arange(1, 257, dtype=np.uint64) * BASE)
_BLANK = np.zeros(256, bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse, for at least ``n`` places."""
    if "up" not in _powers or len(_powers["up"]) < n:
        size = max(n, 1 << 20)
        inverse = np.uint64(pow(int(BASE), -1, 1 << 64))
        for name, base in (("up", BASE), ("down", inverse)):
            step = np.full(size, base, np.uint64)
            step[0] = 1
            _powers[name] = np.multiply.accumulate(step)
    return _powers["up"], _powers["down"]


def paragraphs(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Text number and digest of every distinct paragraph, sorted by both."""
    raws = [t.encode("utf-8") for t in texts]
    ends = np.cumsum(np.fromiter(map(len, raws), np.int64, len(raws)))
    n = int(ends[-1]) if len(ends) else 0
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    raw = np.frombuffer(b"".join(raws), np.uint8)
    edge = np.zeros(n + 1, bool)  # where a text begins
    edge[0] = True
    edge[ends] = True
    word = ~_BLANK[raw]
    before = np.concatenate([[False], word[:-1]])
    begin = np.flatnonzero(word & (~before | edge[:-1]))
    if not len(begin):
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    after = np.concatenate([word[1:], [False]])
    end = np.flatnonzero(word & (~after | edge[1:])) + 1
    up, down = _power(n)
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(BYTE[raw] * up[:n], dtype=np.uint64)])
    hashed = mix((sums[end] - sums[begin]) * down[begin])
    owner = np.searchsorted(ends, begin, side="right")
    lines = np.cumsum(raw == 10)[begin]
    # A paragraph ends at its line's end, or after a word whose hash is divisible by RUN.
    opens = np.ones(len(begin), bool)
    opens[1:] = (owner[1:] != owner[:-1]) | (lines[1:] != lines[:-1]) | (hashed[:-1] % np.uint64(RUN) == 0)
    first = np.flatnonzero(opens)
    last = np.append(first[1:], len(begin)) - 1
    digest = mix((sums[end[last]] - sums[begin[first]]) * down[begin[first]] + np.uint64(1))
    owner = owner[first]
    order = np.lexsort((digest, owner))
    owner, digest = owner[order], digest[order]
    new = np.ones(len(owner), bool)
    new[1:] = (owner[1:] != owner[:-1]) | (digest[1:] != digest[:-1])
    return owner[new], digest[new]


def _places(digest: np.ndarray, cells: int) -> list[np.ndarray]:
    third = cells // 3
    return [(mix(digest ^ s) % np.uint64(third)).astype(np.int64) + j * third for j, s in enumerate(SEEDS)]


class Sketches:
    """The cells of many sets side by side."""

    def __init__(self, sets: int, cells: int):
        self.cells = cells
        self.count = np.zeros(sets * cells, np.int64)
        self.keys = np.zeros(sets * cells, np.uint64)
        self.checks = np.zeros(sets * cells, np.uint64)

    def add(self, owner: np.ndarray, digest: np.ndarray, sign: np.ndarray | int = 1) -> None:
        s = np.broadcast_to(np.asarray(sign, np.int64), digest.shape)
        signed = s.astype(np.uint64)  # -1 is all ones: products wrap to negatives
        check = mix(digest ^ CHECK)
        for place in _places(digest, self.cells):
            at = owner * self.cells + place
            np.add.at(self.count, at, s)
            np.add.at(self.keys, at, digest * signed)
            np.add.at(self.checks, at, check * signed)

    def minus(self, other: "Sketches", sets: np.ndarray) -> "Sketches":
        """The difference of the chosen sets' cells."""
        out = Sketches(0, self.cells)
        for name in ("count", "keys", "checks"):
            mine, theirs = (getattr(x, name).reshape(-1, self.cells)[sets] for x in (self, other))
            setattr(out, name, (mine - theirs).reshape(-1))
        return out

    def peel(self, sets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Owner, digest and sign of what differs, as far as peeling comes, and which sets emptied."""
        found = []
        while True:
            at = np.flatnonzero(np.abs(self.count) == 1)
            sign = self.count[at]
            key = self.keys[at] * sign.astype(np.uint64)
            pure = self.checks[at] * sign.astype(np.uint64) == mix(key ^ CHECK)
            at, sign, key = at[pure], sign[pure], key[pure]
            if not len(at):
                break
            owner = at // self.cells
            order = np.lexsort((key, owner))
            owner, key, sign = owner[order], key[order], sign[order]
            new = np.ones(len(owner), bool)
            new[1:] = (owner[1:] != owner[:-1]) | (key[1:] != key[:-1])
            owner, key, sign = owner[new], key[new], sign[new]
            self.add(owner, key, -sign)
            found.append((owner, key, sign))
        full = (self.count != 0) | (self.keys != 0) | (self.checks != 0)
        owner, key, sign = (np.concatenate(c) for c in zip(*found)) if found else (np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.int64))
        return owner, key, sign, ~full.reshape(sets, self.cells).any(1)

    def packed(self) -> np.ndarray:
        out = np.zeros((len(self.count) // self.cells, self.cells), CELL)
        for name in CELL.names:
            out[name] = getattr(self, name).reshape(-1, self.cells)
        return out


def sketched(units: tuple, sets: int, cells: int = CELLS) -> Sketches:
    out = Sketches(sets, cells)
    out.add(*units)
    return out


def recovered(a: tuple, b: tuple, sets: int, stored: tuple[Sketches, Sketches] | None = None, cells: int = CELLS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Set, digest and sign (1 only in ``a``, -1 only in ``b``) of all differences; both are (owner, digest).

    The first try subtracts the ``stored`` sketches, if they are given; sets that do not peel are
    sketched again with ``GROW`` times the cells.
    """
    gap = np.abs(np.bincount(a[0], minlength=sets) - np.bincount(b[0], minlength=sets))
    open_sets = np.ones(sets, bool)
    out = []
    while open_sets.any():
        # Sets whose sizes alone differ by more than a sketch can hold wait for a larger one.
        now = open_sets & (gap * 1.2 <= cells)
        if now.any():
            index = np.cumsum(now) - 1
            total = int(now.sum())
            if stored is not None and stored[0].cells == cells:
                s = stored[0].minus(stored[1], now)
            else:
                s = Sketches(total, cells)
                for (owner, digest), sign in ((a, 1), (b, -1)):
                    mine = now[owner]
                    s.add(index[owner[mine]], digest[mine], sign)
            owner, key, sign, done = s.peel(total)
            which = np.flatnonzero(now)
            keep = done[owner]
            out.append((which[owner[keep]], key[keep], sign[keep]))
            open_sets[which[done]] = False
        cells *= GROW
    return tuple(np.concatenate(c) for c in zip(*out)) if out else (np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.int64))


def differences(a: tuple, b: tuple, sets: int, stored: tuple[Sketches, Sketches] | None = None, cells: int = CELLS) -> tuple[np.ndarray, np.ndarray]:
    """How many digests only ``a`` and only ``b`` has, per set."""
    owner, _, sign = recovered(a, b, sets, stored, cells)
    return np.bincount(owner[sign > 0], minlength=sets), np.bincount(owner[sign < 0], minlength=sets)


def likeness(a: tuple, b: tuple, sets: int, stored: tuple[Sketches, Sketches] | None = None) -> np.ndarray:
    only_a, only_b = differences(a, b, sets, stored)
    common = np.bincount(a[0], minlength=sets) - only_a
    union = common + only_a + only_b
    return np.where(union > 0, common / np.maximum(union, 1), 1.0)


def fingerprints(texts: list[str], units: tuple, sketch: Sketches | None = None) -> list[str]:
    """Digest of the text, number of paragraphs, and the sketch's cells, as one string."""
    sketch = sketch or sketched(units, len(texts))
    n = np.bincount(units[0], minlength=len(texts))
    return [f"{xxhash.xxh3_64_hexdigest(t.encode('utf-8'))}:{k}:{b64encode(c.tobytes()).decode()}" for t, k, c in zip(texts, n, sketch.packed())]


def read(fingerprint: str) -> tuple[str, int, Sketches]:
    """The text's digest, the number of its paragraphs, and the sketch that a fingerprint holds."""
    digest, n, cells = fingerprint.split(":")
    packed = np.frombuffer(b64decode(cells), CELL)
    out = Sketches(1, len(packed))
    out.count, out.keys, out.checks = packed["count"].astype(np.int64), packed["keys"].copy(), packed["checks"].copy()
    return digest, int(n), out


def compare(a: str, b: str) -> tuple[list[int], list[int], float] | None:
    """Digests only in ``a`` and only in ``b``, and the likeness, from two stored fingerprints.

    None where too much differs for the stored cells: then the texts must be sketched larger.
    """
    (same_a, n, x), (same_b, _, y) = read(a), read(b)
    if same_a == same_b:
        return [], [], 1.0
    if x.cells != y.cells:
        raise ValueError("fingerprints of different sizes do not subtract")
    _, key, sign, done = x.minus(y, np.ones(1, bool)).peel(1)
    if not done[0]:
        return None
    only_a, only_b = sorted(key[sign > 0].tolist()), sorted(key[sign < 0].tolist())
    union = n + len(only_b)
    return only_a, only_b, (n - len(only_a)) / union if union else 1.0


def changed(versions: DataFrame, id_col: str, before: str, after: str) -> DataFrame:
    """id, and the digests of the paragraphs that only the text ``before`` or only ``after`` has, as signed longs."""
    picked = versions.select(F.col(id_col).cast("long").alias("id"), *(F.coalesce(F.col(c).cast("string"), F.lit("")).alias(n) for c, n in ((before, "a"), (after, "b"))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, one in slabs(batch.column(1)):
                other = batch.column(2).slice(lo, hi - lo).to_pylist()
                owner, key, sign = recovered(paragraphs(one), paragraphs(other), hi - lo)
                order = np.lexsort((key, owner))
                owner, key, sign = owner[order], key[order].view(np.int64), sign[order]
                cols = []
                for s in (1, -1):
                    mine = sign == s
                    at = np.searchsorted(owner[mine], np.arange(hi - lo + 1))
                    cols.append(pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(key[mine], pa.int64())))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), *cols], names=["id", "removed", "added"])

    return picked.mapInArrow(run, "id long, removed array<long>, added array<long>")


def fingerprint(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and fingerprint of every row."""
    return per_document(docs, lambda texts: [fingerprints(texts, paragraphs(texts))], "fingerprint string", id_col, text_col)


def edit(text: str, following: str) -> str:
    k = len(text) // 3
    return text[: len(text) - k] + following[:k]


def _chain(rows: list[tuple[int | None, str]]) -> pa.RecordBatch:
    """Results of all rows but the last; each is compared with the one behind it."""
    ids, texts = [r[0] for r in rows], [r[1] for r in rows]
    k = len(rows) - 1
    edited = [edit(t, f) for t, f in zip(texts, texts[1:])]
    own, new = paragraphs(texts), paragraphs(edited)
    here, behind = own[0] < k, own[0] > 0
    a, following = (own[0][here], own[1][here]), (own[0][behind] - 1, own[1][behind])
    mine, theirs, next_ones = sketched(a, k), sketched(new, k), sketched(following, k)
    return pa.RecordBatch.from_arrays(
        [
            pa.array(ids[:k], pa.int64()),
            pa.array([len(t) for t in texts[:k]], pa.int64()),
            pa.array([sha256(t.encode("utf-8")).hexdigest() for t in edited]),
            pa.array(fingerprints(texts[:k], a, mine)),
            pa.array(fingerprints(edited, new, theirs)),
            pa.array(likeness(a, new, k, (mine, theirs))),
            pa.array(likeness(a, following, k, (mine, next_ones))),
        ],
        names=["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"],
    )


def _walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come by bin, in order, then the copies of the row that follows the bin's last."""
    rows: list[tuple] = []
    at, over, size = None, False, 0
    for batch in batches:
        for bin_, copy, doc_id, text in zip(*(c.to_pylist() for c in batch.columns)):
            if bin_ != at:
                rows, at, over, size = [], bin_, False, 0
            if over:  # copies of further rows with the same id
                continue
            rows.append((doc_id, text))
            size += len(text)
            if len(rows) > 1 and (copy or size > SLAB):
                yield _chain(rows)
                rows, size = rows[-1:], len(text)
            over = copy


def with_next(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bins: int | None = None) -> DataFrame:
    """Fingerprints of every row and of its edit, and their likeness to it and to the next row.

    The next row is that of the next smaller id, after the smallest that of the largest.  Ids are
    cut into bins at approximate quantiles, as many as the input's bytes ask for, one shuffle brings each bin's texts together, and the
    first row of a bin is also sent to the bin before, so no task sees more than its bin.
    """
    spark = docs.sparkSession
    bins = bins or min(MOST_BINS, max(4 * int(spark.conf.get("spark.sql.shuffle.partitions")), plan_bytes(docs) // BIN_BYTES))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    rows = rows.withColumn("_k", F.coalesce("doc_id", F.lit(-(2**63))))
    cuts = rows.select(F.percentile_approx("_k", [i / bins for i in range(1, bins)], min(20 * bins, 100_000)).alias("c")).first()["c"] or []
    cuts = sorted(set(cuts))
    # Two levels keep the search short: the coarse cut, then its own fine ones.
    wide = max(1, int(len(cuts) ** 0.5))
    groups = [cuts[i : i + wide] for i in range(0, len(cuts), wide)]
    key = F.col("_k")
    if groups:
        coarse = F.size(F.filter(F.lit([g[0] for g in groups]), lambda c: c <= key))
        fine = F.array(*(F.lit(g) for g in groups))
        inside = F.size(F.filter(F.element_at(fine, F.greatest(coarse, F.lit(1))), lambda c: c <= key))
        upward = F.when(coarse == 0, 0).otherwise((coarse - 1) * wide + inside)
        rows = rows.withColumn("_bin", F.lit(len(cuts)) - upward)
    else:
        rows = rows.withColumn("_bin", F.lit(0))
    heads = [(r["_bin"], r["k"]) for r in rows.groupBy("_bin").agg(F.max("_k").alias("k")).orderBy("_bin").collect()]
    heads = [(b, k, heads[i - 1][0]) for i, (b, k) in enumerate(heads)]
    heads = spark.createDataFrame(heads, "_bin int, _head long, _to int")
    places = F.when(key == F.col("_head"), F.array(F.struct(F.col("_bin").alias("bin"), F.lit(False).alias("copy")), F.struct(F.col("_to").alias("bin"), F.lit(True).alias("copy")))).otherwise(
        F.array(F.struct(F.col("_bin").alias("bin"), F.lit(False).alias("copy")))
    )
    dealt = rows.join(F.broadcast(heads), "_bin").select(F.explode(places).alias("_p"), "doc_id", "text", "_k")
    dealt = dealt.select("_p.bin", "_p.copy", "doc_id", "text", "_k").repartition(bins, "bin")
    ordered = dealt.sortWithinPartitions("bin", "copy", F.col("_k").desc(), F.xxhash64("text"))
    schema = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
    return ordered.select("bin", "copy", "doc_id", "text").mapInArrow(_walk, schema)


def op1_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return with_next(documents(spark, sf_dir))
