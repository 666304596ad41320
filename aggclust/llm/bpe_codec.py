"""Byte-level BPE encoding and decoding.

The vectorised scanner finds the pieces of a slab of texts, cached pair merging turns each piece
into ids, and the byte offset of every token is kept, so any range of ids decodes to its slice of
the text.  Decoding puts the bytes of every token at its offset, for all tokens of a slab at once.

Defined cases: a null text is encoded as empty (no ids, empty bytes); strings that look like
special tokens are ordinary text; ids outside the vocabulary raise ValueError when decoding;
repeated ids and rows each give a row; very long pieces take O(n log n); an empty table gives no
rows.  Other columns are ignored.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator
from functools import lru_cache
from hashlib import sha256
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aggclust.llm import pretokenize
from aggclust.llm.batches import documents, per_document
from aggclust.llm.merging import Batch, TwoPart, merge_linked

#: Bytes of the cache of a Python worker, and tokens whose bytes are placed together.
CACHE, PLACED = 64_000_000, 200_000
#: Pieces looked up together, and bytes of a piece up to which new ones are merged side by side.
BLOCK, SHORT = 200_000, 64


class Codec:
    def __init__(self, path: str):
        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.ranks = ranks
        self.pieces: list[bytes | None] = [None] * (max(ranks.values()) + 1)
        for piece, rank in ranks.items():
            self.pieces[rank] = piece
        self.decimals = [str(i) for i in range(len(self.pieces))]
        self.lengths = np.array([len(p or b"") for p in self.pieces], np.int64)
        self.bytes = np.frombuffer(b"".join(p or b"" for p in self.pieces), np.uint8)
        self.begins = np.cumsum(self.lengths) - self.lengths
        self.known = np.array([p is not None for p in self.pieces])
        self.ids = list(range(len(self.pieces)))  # one object per id, however many pieces hold it
        self.single = [ranks[bytes([b])] for b in range(256)]
        # Every way in which two tokens join to a third.
        self.joins = {ranks[p[:i]] << 20 | ranks[p[i:]]: r for p, r in ranks.items() for i in range(1, len(p)) if p[:i] in ranks and p[i:] in ranks}
        self.batch, self.single_of = Batch(self.joins, 20), np.array(self.single, np.int64)
        self.cache = TwoPart(CACHE, self._piece)

    def _piece(self, piece: str) -> tuple[int, ...]:
        raw = piece.encode("utf-8")
        if raw in self.ranks:
            return (self.ranks[raw],)
        return tuple(map(self.ids.__getitem__, merge_linked([self.single[b] for b in raw], self.joins, 20, 0)[0]))

    def _values(self, pieces: list[str]) -> list[tuple[int, ...]]:
        """Ids of each piece; those that the cache does not hold are merged together."""
        cache, found = self.cache, {}
        short, raws = [], []
        for p in set(pieces):
            value = cache.get(p)
            if value is None:
                value = cache.older.get(p)
                if value is None:
                    raw = p.encode("utf-8")
                    if len(raw) <= SHORT and raw not in self.ranks:
                        short.append(p)
                        raws.append(raw)
                        continue
                    value = self._piece(p)
                cache.put(p, value)
            found[p] = value
        if short:
            symbols = self.single_of[np.frombuffer(b"".join(raws), np.uint8)]
            for p, ids in zip(short, self.batch.merge(symbols, np.fromiter(map(len, raws), np.int64, len(raws)))):
                found[p] = cache.put(p, tuple(map(self.ids.__getitem__, ids)))
        return list(map(found.__getitem__, pieces))

    def encode(self, texts: list[str]) -> Iterator[list[int]]:
        """Ids of each text in turn."""
        joined, bounds, first = pretokenize.starts(texts)
        at, first = bounds.tolist(), first.tolist()
        values: list[tuple[int, ...]] = []
        for lo in range(0, len(at) - 1, BLOCK):
            values += self._values(list(map(joined.__getitem__, map(slice, at[lo : lo + BLOCK], at[lo + 1 : lo + BLOCK + 1]))))
        for a, b in zip(first, first[1:]):
            yield list(chain.from_iterable(values[a:b]))

    def offsets(self, ids: list[int] | np.ndarray) -> np.ndarray:
        """Byte offset at which each token begins, and the end."""
        return np.concatenate([[0], np.cumsum(self.lengths[np.asarray(ids, np.int64)])]).astype(np.int64)

    def placed(self, ids: np.ndarray) -> tuple[bytes, np.ndarray]:
        """The bytes of all ``ids``, each token's at its offset, and the offsets."""
        if len(ids) and not (ids.min() >= 0 and ids.max() < len(self.known) and self.known[ids].all()):
            raise ValueError("an id is not in the vocabulary")
        at = self.offsets(ids)
        out = np.empty(int(at[-1]), np.uint8)
        for lo in range(0, len(ids), PLACED):
            part = ids[lo : lo + PLACED]
            first, last = at[lo], at[lo + len(part)]
            out[first:last] = self.bytes[np.repeat(self.begins[part] - at[lo : lo + len(part)], self.lengths[part]) + np.arange(first, last)]
        return out.tobytes(), at

    def decode_all(self, ids: list[list[int]]) -> list[bytes]:
        flat = np.fromiter(chain.from_iterable(ids), np.int64)
        raw, at = self.placed(flat)
        ends = np.concatenate([[0], np.cumsum([len(i) for i in ids])]).astype(np.int64)
        return [raw[at[a] : at[b]] for a, b in zip(ends, ends[1:])]

    def decode(self, ids: list[int]) -> bytes:
        return self.decode_all([ids])[0]


@lru_cache(maxsize=2)
def codec(path: str) -> Codec:
    return Codec(path)


def encode(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids, offsets: the tokens of every text and the byte at which each begins."""

    def work(texts: list[str]) -> list:
        c = codec(path)
        ids = list(c.encode(texts))
        return [pa.array(ids, pa.list_(pa.int32())), pa.array([c.offsets(i)[:-1] for i in ids], pa.list_(pa.int64()))]

    return per_document(docs, work, "ids array<int>, offsets array<long>", id_col, text_col)


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """doc_id, decoded (binary) from doc_id, ids; null ids decode to no bytes."""

    def run(batches):
        c = codec(path)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(c.decode_all([i or [] for i in b.column(1).to_pylist()]), pa.binary())], names=["doc_id", "decoded"])

    return encoded.select(F.col("doc_id").cast("long"), "ids").mapInArrow(run, "doc_id long, decoded binary")


def round_trip(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Digests of the ids of every text and of the bytes that they decode to."""

    def work(texts: list[str]) -> list[list]:
        c = codec(path)
        ids = list(c.encode(texts))
        by_ids = [sha256(" ".join(map(c.decimals.__getitem__, i)).encode()).hexdigest() for i in ids]
        return [list(map(len, ids)), by_ids, [sha256(raw).hexdigest() for raw in c.decode_all(ids)]]

    return per_document(docs, work, "n_tokens long, ids_sha256 string, decoded_sha256 string", id_col, text_col)


def op8_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return round_trip(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.tiktoken"))
