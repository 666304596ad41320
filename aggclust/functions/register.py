"""The features' functions under SQL names."""

from __future__ import annotations

from pyspark.sql import SparkSession

_CF = "STRUCT<n: DOUBLE, mu: ARRAY<DOUBLE>, sse: DOUBLE>"
_GAP2 = "aggregate(zip_with(a.mu, b.mu, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)"
_UNION = f"(a.sse + b.sse + a.n * b.n / (a.n + b.n) * {_GAP2})"
_BODIES = {
    "cf_d0": f"sqrt({_GAP2})",
    "cf_d1": "aggregate(zip_with(a.mu, b.mu, (x, y) -> abs(x - y)), 0D, (s, x) -> s + x)",
    "cf_d2": f"sqrt(a.sse / a.n + b.sse / b.n + {_GAP2})",
    "cf_d3": f"CASE WHEN a.n + b.n > 1 THEN sqrt(2 * {_UNION} / (a.n + b.n - 1)) ELSE 0D END",
    "cf_d4": f"sqrt(a.n * b.n / (a.n + b.n) * {_GAP2})",
    "cf_r": f"sqrt({_UNION} / (a.n + b.n))",
}


def register(spark: SparkSession) -> None:
    """``cf_merge``, ``cf_d0`` to ``cf_r`` as SQL functions that Catalyst inlines, and ``merge_steps`` as a table function."""
    merged = f"named_struct('n', a.n + b.n, 'mu', zip_with(a.mu, b.mu, (x, y) -> x + (y - x) * (b.n / (a.n + b.n))), 'sse', {_UNION})"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION cf_merge(a {_CF}, b {_CF}) RETURNS {_CF} RETURN {merged}")
    for name, body in _BODIES.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(a {_CF}, b {_CF}) RETURNS DOUBLE RETURN {body}")

    from pyspark.sql.functions import udtf

    @udtf(returnType="step int, a int, b int, height double")
    class MergeSteps:
        def eval(self, vectors: list, kind: str):
            import numpy as np

            from aggclust.operators import agglomerate as agg

            x = np.array(vectors, float)
            ones = np.ones(len(x))
            for step, left, right, _, h, _ in agg.number(agg.agglomerate_cf(ones, x, np.zeros(len(x)), kind, "scan"), ones):
                yield step, min(left, right), max(left, right), h

    spark.udtf.register("merge_steps", MergeSteps)
