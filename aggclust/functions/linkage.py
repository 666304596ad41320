"""Linkages: recurrence coefficients, seeds, closed forms.

new = alpha_a d(A,C) + alpha_b d(B,C) + beta d(A,B) + gamma |d(A,C) - d(B,C)|, with coefficients
that may depend on the three sizes.  Works on columns and on numbers or arrays alike.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Linkage:
    name: str
    weights: Callable  # sizes (a, b, c) -> alpha_a, alpha_b, beta, gamma
    squared: bool  # whether the matrix must be seeded with squared distances
    cf_kind: str | None  # the matching distance of features
    cf_factor: float = 1.0
    cf_exact: bool = True
    reducible: bool = True


def _shares(a, b, c):
    return a / (a + b), b / (a + b)


LINKAGES = {
    link.name: link
    for link in (
        Linkage("single", lambda a, b, c: (0.5, 0.5, 0.0, -0.5), False, None),
        Linkage("complete", lambda a, b, c: (0.5, 0.5, 0.0, 0.5), False, None),
        Linkage("upgma", lambda a, b, c: (*_shares(a, b, c), 0.0, 0.0), False, "D2"),
        Linkage("wpgma", lambda a, b, c: (0.5, 0.5, 0.0, 0.0), False, "D2", cf_exact=False),
        Linkage("upgmc", lambda a, b, c: (*_shares(a, b, c), -(a * b) / ((a + b) * (a + b)), 0.0), True, "D0", reducible=False),
        Linkage("wpgmc", lambda a, b, c: (0.5, 0.5, -0.25, 0.0), True, "D0", cf_exact=False, reducible=False),
        Linkage("ward", lambda a, b, c: ((a + c) / (a + b + c), (b + c) / (a + b + c), -c / (a + b + c), 0.0), True, "D4", cf_factor=2.0),
    )
}


#: Linkages without recurrence: taken anew from all distances of the two clusters' members.
BY_DEFINITION = ("minimax", "medoid")


def by_definition(name: str, d: np.ndarray, a: np.ndarray, b: np.ndarray) -> float:
    """Of members ``a`` and ``b`` in a matrix with zero diagonal.

    ``minimax``: the least radius around a member that holds both clusters.  ``medoid``: the
    distance of the members of least summed distance to their own cluster.
    """
    if name == "minimax":
        both = np.concatenate([a, b])
        return float(d[np.ix_(both, both)].max(1).min())
    if name == "medoid":
        centre = [m[int(d[np.ix_(m, m)].sum(1).argmin())] for m in (a, b)]
        return float(d[centre[0], centre[1]])
    raise ValueError(f"{name} has a recurrence")


def get(name: str) -> Linkage:
    if name not in LINKAGES:
        raise ValueError(f"unknown linkage {name}; there are {', '.join(LINKAGES)}")
    return LINKAGES[name]


def coefficients(name: str, na, nb, nc):
    return get(name).weights(na, nb, nc)


def recur(name: str, dac, dbc, dab, na=1.0, nb=1.0, nc=1.0):
    """The distance of the union of A and B to C; columns, numbers or arrays."""
    if name in ("single", "complete"):
        low = name == "single"
        if isinstance(dac, Column):
            return F.least(dac, dbc) if low else F.greatest(dac, dbc)
        return np.minimum(dac, dbc) if low else np.maximum(dac, dbc)
    x, y, beta, _ = coefficients(name, na, nb, nc)
    return x * dac + y * dbc + beta * dab


def initial(name: str, base: str = "euclidean") -> tuple[bool, str | None]:
    """Whether to seed squared, and the features' distance that seeds the same linkage."""
    link = get(name)
    return link.squared or base == "sqeuclidean", link.cf_kind


def closed_form(name: str, a: np.ndarray, b: np.ndarray, squared: bool = False) -> float:
    """The linkage of two point sets by definition; the two weighted ones have none."""
    cross = ((a[:, None, :] - b[None, :, :]) ** 2).sum(-1)
    d = cross if squared else np.sqrt(cross)
    between = float(((a.mean(0) - b.mean(0)) ** 2).sum())
    forms = {"single": d.min, "complete": d.max, "upgma": d.mean, "upgmc": lambda: between, "ward": lambda: 2 * len(a) * len(b) / (len(a) + len(b)) * between}
    if name not in forms:
        raise ValueError(f"{name} is defined by its recurrence alone")
    return float(forms[name]())


def coefficient_table(sizes: DataFrame, *keep: str) -> DataFrame:
    """A row per linkage for each row of sizes (na, nb, nc), with the columns ``keep``."""
    value = lambda x: x if isinstance(x, Column) else F.lit(float(x))
    names = ("alpha_a", "alpha_b", "beta", "gamma")
    row = lambda n: F.struct(F.lit(n).alias("linkage"), *(value(x).alias(c) for x, c in zip(coefficients(n, *map(F.col, ("na", "nb", "nc"))), names)))
    return sizes.select(*keep, F.inline(F.array(*map(row, LINKAGES))))


def linkage_between(points: DataFrame, group: str, vec: str, name: str, squared: bool = False) -> DataFrame:
    """The linkage of every two groups of points.

    Centroid, Ward and the mean of squared distances follow from counts, means and squared
    deviations; single, complete and the mean distance need the cross pairs, taken in blocks.
    """
    from aggclust.functions.features import gap, square_norm
    from aggclust.operators.blocks import group_linkage

    if name in ("upgmc", "ward") or (name == "upgma" and squared):
        from aggclust.functions.features import cf_agg

        d = len(points.select(vec).first()[0])
        flat = points.select(group, *(F.col(vec)[i].alias(f"_{i}") for i in range(d)))
        feats = cf_agg(flat, [group], [f"_{i}" for i in range(d)])
        a, b = feats.select(F.col(group).alias("a"), F.col("cf").alias("x")), feats.select(F.col(group).alias("b"), F.col("cf").alias("y"))
        d2 = square_norm(gap(F.col("x.mu"), F.col("y.mu")))
        within = F.col("x.sse") / F.col("x.n") + F.col("y.sse") / F.col("y.n")
        value = {"upgmc": d2, "ward": 2 * F.col("x.n") * F.col("y.n") / (F.col("x.n") + F.col("y.n")) * d2, "upgma": within + d2}[name]
        return a.join(b, F.col("a") < F.col("b")).select("a", "b", value.alias("d"))
    return group_linkage(points, group, vec, name, squared)
