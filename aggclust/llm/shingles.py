"""Hashed word shingles of many texts at once."""

from __future__ import annotations

import numpy as np

from aggclust.llm.fingerprints import BYTE, _power, mix

WORDS = 5
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[ord("A") : ord("Z") + 1] += 32
_IN_WORD = np.zeros(256, bool)
_IN_WORD[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True
_TURN = mix(np.arange(1, 65, dtype=np.uint64)) | np.uint64(1)


def shingles(texts: list[str], width: int = WORDS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Text number, hash and number of occurrences of every distinct shingle, sorted.

    Words are runs of letters and digits (every character beyond ASCII counts), ASCII case folded.
    A text of fewer than ``width`` words is one shingle; one without words has none.
    """
    none = np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.int64)
    raws = [t.encode("utf-8") for t in texts]
    ends = np.cumsum(np.fromiter(map(len, raws), np.int64, len(raws)))
    n = int(ends[-1]) if len(ends) else 0
    if not n:
        return none
    raw = np.frombuffer(b"".join(raws), np.uint8)
    edge = np.zeros(n + 1, bool)
    edge[0] = True
    edge[ends] = True
    word = _IN_WORD[raw]
    begin = np.flatnonzero(word & (~np.concatenate([[False], word[:-1]]) | edge[:-1]))
    if not len(begin):
        return none
    end = np.flatnonzero(word & (~np.concatenate([word[1:], [False]]) | edge[1:])) + 1
    up, down = _power(n)
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(BYTE[_FOLD[raw]] * up[:n], dtype=np.uint64)])
    hashed = mix((sums[end] - sums[begin]) * down[begin])
    owner = np.searchsorted(ends, begin, side="right")
    per = np.bincount(owner, minlength=len(texts))
    k = len(hashed)
    total = np.zeros(k, np.uint64)
    for i in range(min(width, k)):
        total[: k - i] += hashed[i:] * _TURN[i]
    upto = np.cumsum(per)
    left = upto[owner] - np.arange(k)  # words from here to the text's end
    whole = left >= width
    # Short texts: the sum over all their words, from their first word on.
    short = (per[owner] < width) & (left == per[owner])
    for at in np.flatnonzero(short):
        m = int(left[at])
        total[at] = np.sum(hashed[at : at + m] * _TURN[:m], dtype=np.uint64) + np.uint64(m)
    use = whole | short
    owner, digest = owner[use], mix(total[use])
    order = np.lexsort((digest, owner))
    owner, digest = owner[order], digest[order]
    new = np.ones(len(owner), bool)
    new[1:] = (owner[1:] != owner[:-1]) | (digest[1:] != digest[:-1])
    at = np.flatnonzero(new)
    return owner[at], digest[at], np.diff(np.append(at, len(owner)))
