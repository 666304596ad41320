"""Pre-tokenisation of many texts at once without a regular-expression engine.

Each code point becomes a symbol, each symbol a function from the scanner's state before it to
the state after it.  Those functions form a small finite monoid, so composing them is one table
look-up and the states of a whole slab come from an associative scan: blocks are composed side
by side, the blocks' totals are folded, and a second pass yields the state before every code
point, hence the places where pieces begin.
"""

from __future__ import annotations

import numpy as np
import regex

LETTER, NUMBER, OTHER, SPACE, BLANK = range(5)

# The code points of Unicode's White_Space property.
WHITE_SPACE = [*range(0x09, 0x0E), 0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]

# Symbols.  A blank is "last" if a non-blank follows it in the same text.
S_LETTER, S_NUMBER, S_OTHER, S_SPACE_LAST, S_BLANK_LAST, S_BLANK_MORE, S_SHORT, S_LONG = range(8)
# States after a code point.  FREE: whatever follows begins a piece; JOIN: a space that joins what follows.
FREE, IN_LETTERS, IN_NUMBERS, IN_OTHERS, JOIN, IN_BLANKS, ONE_LEFT, TWO_LEFT = range(8)


def _classes() -> np.ndarray:
    table = np.full(0x110000, OTHER, np.uint8)
    points = "".join(map(chr, [*range(0xD800), *range(0xE000, 0x110000)]))
    number = np.array([*range(0xD800), *range(0xE000, 0x110000)])
    for kind, pattern in ((LETTER, r"\p{L}+"), (NUMBER, r"\p{N}+")):
        for m in regex.finditer(pattern, points):
            table[number[m.start() : m.end()]] = kind
    table[WHITE_SPACE] = BLANK
    table[0x20] = SPACE
    return table


def _machine() -> tuple[np.ndarray, np.ndarray]:
    """after[state, symbol] and begins[state, symbol]."""
    after, begins = np.zeros((8, 8), np.uint8), np.ones((8, 8), bool)
    fresh = {S_LETTER: IN_LETTERS, S_NUMBER: IN_NUMBERS, S_OTHER: IN_OTHERS, S_SPACE_LAST: JOIN, S_BLANK_LAST: FREE, S_BLANK_MORE: IN_BLANKS, S_SHORT: ONE_LEFT, S_LONG: TWO_LEFT}
    goes_on = {IN_LETTERS: {S_LETTER}, IN_NUMBERS: {S_NUMBER}, IN_OTHERS: {S_OTHER, S_SHORT, S_LONG}, IN_BLANKS: {S_BLANK_MORE}}
    for state in range(8):
        for symbol, to in fresh.items():
            after[state, symbol] = to
            if symbol in goes_on.get(state, ()):
                begins[state, symbol], after[state, symbol] = False, state
            elif state == JOIN and symbol in (S_LETTER, S_NUMBER, S_OTHER, S_SHORT, S_LONG):
                begins[state, symbol] = False
                after[state, symbol] = {S_LETTER: IN_LETTERS, S_NUMBER: IN_NUMBERS}.get(symbol, IN_OTHERS)
            elif state in (ONE_LEFT, TWO_LEFT):
                begins[state, symbol], after[state, symbol] = False, FREE if state == ONE_LEFT else ONE_LEFT
    return after, begins


def _monoid(after: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All compositions of the symbols' functions: their value tables, and compose[f, g] = f then g.

    The first 8 are the symbols inside a text; the next 8 the same symbols at a text's beginning,
    which forget the state before them.
    """
    found: dict[tuple, int] = {}
    tables: list[tuple] = []

    def number(f: tuple) -> int:
        if f not in found:
            found[f] = len(tables)
            tables.append(f)
        return found[f]

    gens = [tuple(after[:, s]) for s in range(8)] + [(after[FREE, s],) * 8 for s in range(8)]
    alias = [number(g) for g in gens]
    at = 0
    while at < len(tables):
        for g in gens:
            number(tuple(g[x] for x in tables[at]))
        at += 1
    values = np.array(tables, np.uint8)
    compose = np.array([[found[tuple(values[g][values[f]])] for g in range(len(tables))] for f in range(len(tables))], np.uint16)
    return values, compose, np.array(alias, np.uint16)


CLASS = _classes()
AFTER, BEGINS = _machine()
VALUES, COMPOSE, ALIAS = _monoid(AFTER)


def _symbols(points: np.ndarray, first: np.ndarray) -> np.ndarray:
    kind = CLASS[points]
    n = len(points)
    blank = kind >= SPACE
    last = np.zeros(n, bool)  # of its text
    last[first[1:] - 1] = True
    last[n - 1] = True
    more = np.ones(n, bool)
    more[:-1] = blank[1:]
    more |= last
    symbol = np.where(blank, np.where(more, S_BLANK_MORE, np.where(kind == SPACE, S_SPACE_LAST, S_BLANK_LAST)), kind).astype(np.uint8)
    quote = np.flatnonzero(points == 0x27)
    quote = quote[~last[quote]]
    if len(quote):
        one = points[quote + 1]
        short = np.isin(one, [ord(c) for c in "stmd"])
        room = ~last[quote + 1]
        two = np.zeros(len(quote), points.dtype)
        two[room] = points[quote[room] + 2]
        pair = [(ord(a), ord(b)) for a, b in ("re", "ve", "ll")]
        long = np.zeros(len(quote), bool)
        for a, b in pair:
            long |= (one == a) & (two == b)
        symbol[quote[short]] = S_SHORT
        symbol[quote[long]] = S_LONG
    return symbol


def starts(texts: list[str]) -> tuple[str, np.ndarray, np.ndarray]:
    """The texts joined, the offsets where pieces begin (and the end), and each text's first piece (and the end)."""
    joined = "".join(texts)
    n = len(joined)
    lengths = np.fromiter(map(len, texts), np.int64, len(texts))
    ends = np.cumsum(lengths)
    if not n:
        return joined, np.zeros(1, np.int64), np.zeros(len(texts) + 1, np.int64)
    points = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
    first = (ends - lengths)[lengths > 0]
    symbol = _symbols(points, first)
    opening = np.zeros(n, bool)
    opening[first] = True
    step = ALIAS[symbol + 8 * opening.astype(np.uint8)]

    width = max(16, int(n**0.5))
    rows = -(-n // width)
    grid = np.zeros(rows * width, np.uint16)
    grid[:n] = step
    grid = np.ascontiguousarray(grid.reshape(rows, width).T)
    total = grid[0].copy()
    for j in range(1, width):
        total = COMPOSE[total, grid[j]]
    state = np.empty(rows, np.uint8)
    now = FREE
    for r, f in enumerate(total.tolist()):
        state[r] = now
        now = VALUES[f, now]
    before = np.empty((width, rows), np.uint8)
    for j in range(width):
        before[j] = state
        state = VALUES[grid[j], state]
    before = before.T.reshape(-1)[:n]
    begin = np.flatnonzero(BEGINS[before, symbol] | opening)
    bounds = np.append(begin, n)
    offsets = np.concatenate([[0], ends])
    return joined, bounds, np.searchsorted(begin, offsets)
