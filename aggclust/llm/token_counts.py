"""Token counts by heap-and-linked-list byte-pair merging.

A text is cut into pieces by the vectorised scanner, and a piece's count is the number of its
bytes minus the number of merges that a heap of adjacent pairs performs; no token identifiers
are produced.  Counts of pieces are cached per Python worker in a cache bounded in bytes.

Defined cases: a null text counts as empty (0 bytes, 0 tokens); repeated ids and repeated rows
each give a row; the special string of the vocabulary counts as one token wherever it stands,
which is the library's default; very long pieces take O(n log n); an empty table gives no rows.
Other columns are ignored.
"""

from __future__ import annotations

import json
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from aggclust.llm import pretokenize
from aggclust.llm.batches import documents, per_document
from aggclust.llm.merging import TwoPart, merge_linked

#: Bytes of the cache of a Python worker, and the limit of a document's tokens.
CACHE, LIMIT = 128_000_000, 1024


def byte_letters() -> list[str]:
    """The printable stand-in of every byte in byte-level vocabularies."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    letters, spare = {b: chr(b) for b in plain}, 256
    for b in range(256):
        if b not in letters:
            letters[b] = chr(spare)
            spare += 1
    return [letters[b] for b in range(256)]


@lru_cache(maxsize=2)
def load(path: str) -> tuple[TwoPart, list[str]]:
    """The cached piece counter of a byte-level vocabulary, and its special strings."""
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    number = {letter: b for b, letter in enumerate(byte_letters())}
    merges = [m.split(" ") if isinstance(m, str) else m for m in spec["model"]["merges"]]
    ranks = {}
    for rank, (left, right) in enumerate(merges):
        number[left + right] = 256 + rank
    for rank, (left, right) in enumerate(merges):
        ranks[number[left] << 20 | number[right]] = rank

    def count(piece: str) -> int:
        symbols = list(piece.encode("utf-8"))
        return len(symbols) - merge_linked(symbols, ranks, 20, 256)[1] if len(symbols) > 1 else len(symbols)

    return TwoPart(CACHE, count), [t["content"] for t in spec.get("added_tokens", [])]


def count_texts(texts: list[str], path: str) -> np.ndarray:
    """Tokens of each text."""
    cache, specials = load(path)
    out = np.zeros(len(texts), np.int64)
    owner, parts = list(range(len(texts))), texts
    for special in specials:
        if any(special in p for p in parts):
            cut = [p.split(special) for p in parts]
            for o, p in zip(owner, cut):
                out[o] += len(p) - 1
            owner = [o for o, p in zip(owner, cut) for _ in p]
            parts = [x for p in cut for x in p]
    joined, bounds, first = pretokenize.starts(parts)
    at = bounds.tolist()
    get = cache.__getitem__
    counts = np.fromiter((get(joined[a:b]) for a, b in zip(at, at[1:])), np.int64, len(at) - 1)
    upto = np.concatenate([[0], np.cumsum(counts)])
    np.add.at(out, owner, upto[first[1:]] - upto[first[:-1]])
    return out


def token_counts(docs: DataFrame, path: str, limit: int = LIMIT, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit of every row."""

    def work(texts: list[str]) -> list[list]:
        n = count_texts(texts, path)
        return [[len(t.encode("utf-8")) for t in texts], n, n > limit]

    return per_document(docs, work, "n_bytes long, n_tokens long, over_limit boolean", id_col, text_col)


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return token_counts(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"))
