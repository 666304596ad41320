"""Distances between cluster features: one set of closed forms, as columns and on arrays.

All are computed squared; the root is taken on request.  With D the gap of the means, S the sums
of squares and n the weights: D0 is |D|, D1 the 1-norm of D, D2 the root mean squared distance
across the pair, D3 within the union, D4 the root of the growth of the sum of squares, R the
union's radius.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from aggclust.functions.features import gap, square_norm

KINDS = ("D0", "D1", "D2", "D3", "D4", "R")
#: Merging a nearest pair can bring it nearer to a third: these need not give the greedy tree by chains or rounds.
NOT_REDUCIBLE = ("D0", "D1", "D3", "R")


def _union_sse(a: Column, b: Column, d2: Column) -> Column:
    return a["sse"] + b["sse"] + a["n"] * b["n"] / (a["n"] + b["n"]) * d2


def cf_distance(a: str | Column, b: str | Column, kind: str, squared: bool = False) -> Column:
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    delta = gap(a["mu"], b["mu"])
    d2 = square_norm(delta)
    n = a["n"] + b["n"]
    if kind == "D0":
        out = d2
    elif kind == "D1":
        manhattan = F.aggregate(delta, F.lit(0.0), lambda s, x: s + F.abs(x))
        return manhattan * manhattan if squared else manhattan
    elif kind == "D2":
        out = a["sse"] / a["n"] + b["sse"] / b["n"] + d2
    elif kind == "D3":
        out = F.when(n > 1, 2 * _union_sse(a, b, d2) / (n - 1)).otherwise(0.0)
    elif kind == "D4":
        out = a["n"] * b["n"] / n * d2
    elif kind == "R":
        out = _union_sse(a, b, d2) / n
    else:
        raise ValueError(f"unknown distance {kind}")
    return out if squared else F.sqrt(out)


def distance_profile(pairs: DataFrame, a: str = "a", b: str = "b", keep: tuple[str, ...] = ()) -> DataFrame:
    """All six side by side."""
    return pairs.select(*keep, *(cf_distance(a, b, k).alias(k.lower()) for k in KINDS))


def _squared(kind: str, delta: np.ndarray, axis: int, n, sse, ns: np.ndarray, sses: np.ndarray) -> np.ndarray:
    """The closed forms on arrays; ``delta`` holds the gaps of the means along ``axis``."""
    if kind == "D1":
        return np.abs(delta).sum(axis) ** 2
    d2 = np.einsum("dw,dw->w", delta, delta) if axis == 0 else np.einsum("rdw,rdw->rw", delta, delta)
    if kind == "D0":
        return d2
    if kind == "D2":
        return sse / n + sses / ns + d2
    total = n + ns
    if kind == "D4":
        return n * ns / total * d2
    union = sse + sses + n * ns / total * d2
    if kind == "R":
        return union / total
    if kind == "D3":
        return np.where(total > 1, 2 * union / np.maximum(total - 1, 1e-300), 0.0)
    raise ValueError(f"unknown distance {kind}")


def squared_to_many(kind: str, n: float, mu: np.ndarray, sse: float, ns: np.ndarray, mus: np.ndarray, sses: np.ndarray) -> np.ndarray:
    """Squared distances of one feature to many; ``mus`` is (d, m), one row per dimension."""
    return _squared(kind, mus - mu[:, None], 0, n, sse, ns, sses)


def squared_rows(kind: str, n: np.ndarray, mu: np.ndarray, sse: np.ndarray, ns: np.ndarray, mus: np.ndarray, sses: np.ndarray) -> np.ndarray:
    """Squared distances (r, w) of feature r to the w features of its row; ``mus`` is (r, d, w)."""
    return _squared(kind, mus - mu[:, :, None], 1, n[:, None], sse[:, None], ns, sses)


def squared_matrix(kind: str, n: np.ndarray, mu: np.ndarray, sse: np.ndarray) -> np.ndarray:
    """The full matrix of squared distances of features; ``mu`` is (m, d)."""
    mus = np.ascontiguousarray(mu.T)
    out = np.stack([squared_to_many(kind, n[i], mu[i], sse[i], n, mus, sse) for i in range(len(n))]) if len(n) else np.zeros((0, 0))
    np.fill_diagonal(out, np.inf)
    return out
