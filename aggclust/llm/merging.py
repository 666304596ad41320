"""Byte-pair merging over a heap of adjacent pairs and a linked list of symbols."""

from __future__ import annotations

from heapq import heapify, heappop, heappush

import numpy as np


def merge_linked(symbols: list[int], ranks: dict[int, int], shift: int, made: int) -> tuple[list[int], int]:
    """Merge ``symbols`` by ``ranks``: (left << shift | right) -> rank; merging makes symbol made + rank.

    The heap holds rank and place of every adjacent pair; the lowest rank, leftmost first, is
    popped, stale entries are skipped.  Returns the symbols left and the number of merges;
    O(n log n) for any length.
    """
    n = len(symbols)
    sym = list(symbols)
    before, after = list(range(-1, n - 1)), [*range(1, n), -1]
    get = ranks.get
    heap = []
    for i in range(n - 1):
        r = get(sym[i] << shift | sym[i + 1])
        if r is not None:
            heap.append((r, i))
    heapify(heap)
    merges = 0
    while heap:
        r, i = heappop(heap)
        left = sym[i]
        j = after[i]
        if left < 0 or j < 0 or get(left << shift | sym[j]) != r:
            continue
        merges += 1
        new = sym[i] = made + r
        sym[j] = -1
        k = after[i] = after[j]
        if k >= 0:
            before[k] = i
            r = get(new << shift | sym[k])
            if r is not None:
                heappush(heap, (r, i))
        h = before[i]
        if h >= 0:
            r = get(sym[h] << shift | new)
            if r is not None:
                heappush(heap, (r, h))
    return [s for s in sym if s >= 0], merges


class Batch:
    """The merges of ``merge_linked`` for many short pieces side by side.

    In every round each piece merges its lowest pair, the leftmost on ties; pieces without one are
    done.  Only ranks of pairs next to a merge are looked up again.
    """

    NONE = (1 << 31) - 1

    def __init__(self, ranks: dict[int, int], shift: int):
        keys, values = np.fromiter(ranks, np.int64, len(ranks)), np.fromiter(ranks.values(), np.int64, len(ranks))
        order = np.argsort(keys)
        self.keys, self.values, self.shift = np.append(keys[order], 1 << 62), np.append(values[order], self.NONE), shift

    def rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = left << self.shift | right
        at = np.searchsorted(self.keys, key)
        return np.where(self.keys[at] == key, self.values[at], self.NONE)

    def merge(self, symbols: np.ndarray, sizes: np.ndarray) -> list[list[int]]:
        """Symbols left of each piece; ``symbols`` hold the pieces one after the other, none of them empty."""
        out: list = [None] * len(sizes)
        piece = np.arange(len(sizes))
        sym, size = symbols.astype(np.int64), sizes.astype(np.int64)
        rank = np.full(len(sym), self.NONE, np.int64)  # of each symbol and the next of its piece
        if len(sym) > 1:
            rank[:-1] = self.rank(sym[:-1], sym[1:])
        rank[np.cumsum(size) - 1] = self.NONE
        while len(piece):
            begin = np.cumsum(size) - size
            best = np.minimum.reduceat(rank << 32 | np.arange(len(rank)), begin)
            low = best >> 32
            done = low == self.NONE
            if done.any():
                for k in np.flatnonzero(done).tolist():
                    out[piece[k]] = sym[begin[k] : begin[k] + size[k]].tolist()
                more = np.repeat(~done, size)
                at = np.cumsum(more) - 1
                sym, rank = sym[more], rank[more]
                piece, size, low, best = piece[~done], size[~done], low[~done], best[~done]
                if not len(piece):
                    break
                begin = np.cumsum(size) - size
                where = at[best & 0xFFFFFFFF]
            else:
                where = best & 0xFFFFFFFF
            sym[where] = low
            rank[where] = rank[where + 1]
            kept = np.ones(len(sym), bool)
            kept[where + 1] = False
            sym, rank = sym[kept], rank[kept]
            where = where - np.arange(len(where))  # one symbol went from every piece before
            size = size - 1
            begin = begin - np.arange(len(begin))
            right = where[where + 1 < begin + size]
            rank[right] = self.rank(sym[right], sym[right + 1])
            rank[where[where + 1 == begin + size]] = self.NONE
            left = where[where > begin] - 1
            rank[left] = self.rank(sym[left], sym[left + 1])
        return out


class TwoPart(dict):
    """A cache of texts bounded in bytes: when half of ``limit`` is new, the older half goes.

    A text costs about 240 bytes and 12 for each of its characters, value included; one of more
    than ``LONGEST`` characters is made anew each time.
    """

    LONGEST = 256

    def __init__(self, limit: int, make):
        super().__init__()
        self.half, self.make, self.older, self.held = limit // 2, make, {}, 0

    def __missing__(self, key):
        value = self.older.get(key)
        return self.put(key, self.make(key) if value is None else value)

    def put(self, key, value):
        if len(key) > self.LONGEST:
            return value
        cost = 240 + 12 * len(key)
        if self.held + cost > self.half:
            self.older = dict(self)
            self.clear()
            self.held = 0
        self.held += cost
        self[key] = value
        return value
