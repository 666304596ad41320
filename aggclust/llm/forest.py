"""A small random forest, grown on the driver from a bounded table and applied as SQL."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class Leaf:
    share: float


@dataclass(frozen=True)
class Split:
    feature: int
    cut: float
    low: "Leaf | Split"
    high: "Leaf | Split"


def _best(x: np.ndarray, y: np.ndarray, features: np.ndarray, least: int) -> tuple[float, int, float] | None:
    """The split of lowest Gini impurity: (impurity, feature, cut)."""
    best, n = None, len(y)
    for f in features:
        order = np.argsort(x[:, f], kind="stable")
        v, t = x[order, f], np.cumsum(y[order])
        at = np.flatnonzero(v[1:] > v[:-1]) + 1
        at = at[(at >= least) & (n - at >= least)]
        if not len(at):
            continue
        p, q = t[at - 1] / at, (t[-1] - t[at - 1]) / (n - at)
        impurity = (at * p * (1 - p) + (n - at) * q * (1 - q)) / n
        k = int(np.argmin(impurity))
        if best is None or impurity[k] < best[0] - 1e-12:
            best = float(impurity[k]), int(f), float((v[at[k] - 1] + v[at[k]]) / 2)
    return best


def _grow(x: np.ndarray, y: np.ndarray, depth: int, least: int, rng: np.random.Generator) -> "Leaf | Split":
    share = float(y.mean())
    if depth == 0 or share in (0.0, 1.0) or len(y) < 2 * least:
        return Leaf(share)
    some = np.sort(rng.permutation(x.shape[1])[: max(1, int(round(x.shape[1] ** 0.5)) + 1)])
    found = _best(x, y, some, least)
    if found is None or found[0] >= share * (1 - share) - 1e-12:
        return Leaf(share)
    _, f, cut = found
    low = x[:, f] <= cut
    return Split(f, cut, _grow(x[low], y[low], depth - 1, least, rng), _grow(x[~low], y[~low], depth - 1, least, rng))


def grow(x: np.ndarray, y: np.ndarray, trees: int = 24, depth: int = 7, least: int = 4, seed: int = 11) -> list["Leaf | Split"]:
    """Trees on bootstrap samples with random features at each split; the same input gives the same trees."""
    rng = np.random.default_rng(seed)
    out = []
    for _ in range(trees):
        rows = rng.integers(len(y), size=len(y))
        out.append(_grow(x[rows], y[rows], depth, least, rng))
    return out


def predict(trees: list, x: np.ndarray) -> np.ndarray:
    def one(t, row) -> float:
        while isinstance(t, Split):
            t = t.low if row[t.feature] <= t.cut else t.high
        return t.share

    return np.array([sum(one(t, row) for t in trees) / len(trees) for row in x])


def sql(trees: list, names: list[str]) -> str:
    """The forest as one constant array of node tables, walked by higher-order functions.

    Nodes are numbered from 1; a leaf has feature 0.  The expression's size does not grow with the
    forest's depth, as nested conditions would make generated code do.
    """

    def table(t) -> tuple[str, int]:
        nodes: list[list] = []

        def add(t) -> tuple[int, int]:
            at = len(nodes)
            nodes.append([0, 0.0, 0, 0, 0.0])
            if isinstance(t, Leaf):
                nodes[at][4] = t.share
                return at + 1, 0
            low, d = add(t.low)
            high, e = add(t.high)
            nodes[at] = [t.feature + 1, t.cut, low, high, 0.0]
            return at + 1, 1 + max(d, e)

        depth = add(t)[1]
        kinds = ("", "D", "", "", "D")
        cols = ["array(" + ", ".join(f"{n[i]!r}{kinds[i]}" for n in nodes) + ")" for i in range(5)]
        return f"named_struct('f', {cols[0]}, 'c', {cols[1]}, 'l', {cols[2]}, 'h', {cols[3]}, 's', {cols[4]})", depth

    tables = [table(t) for t in trees]
    deep = max(d for _, d in tables)
    step = "CASE WHEN element_at(t.f, n) = 0 THEN n WHEN element_at(fs, element_at(t.f, n)) <= element_at(t.c, n) THEN element_at(t.l, n) ELSE element_at(t.h, n) END"
    leaf = f"aggregate(sequence(1, {max(deep, 1)}), 1, (n, i) -> {step})"
    total = f"aggregate(array({', '.join(x for x, _ in tables)}), 0D, (a, t) -> a + element_at(t.s, {leaf}))"
    return f"element_at(transform(array(array({', '.join(names)})), fs -> {total}), 1) / {len(trees)}D"
