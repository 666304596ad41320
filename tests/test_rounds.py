import numpy as np
import pytest
from pyspark.sql import functions as F

from aggclust.operators import agglomerate as agg
from aggclust.operators import rounds


def frame(spark, d):
    n = len(d)
    return spark.createDataFrame([(i, j, float(d[i, j])) for i in range(n) for j in range(i + 1, n)], "i long, j long, d double")


@pytest.mark.parametrize("name", ["ward"])
def test_rounds_equal_greedy(spark, name):
    x = np.random.default_rng(3).normal(size=(12, 2))
    d = agg.point_matrix(x, squared=name == "ward")
    sizes = spark.range(12).select("id", F.lit(1.0).alias("n"))
    got = sorted((r.a, r.b, round(r.height, 8)) for r in rounds.reciprocal_rounds(frame(spark, d), sizes, name).collect())
    assert got == sorted((i, j, round(h, 8)) for i, j, h in agg.greedy_scan(d, np.ones(12), name))


def test_rounds_refuse_what_is_not_reducible(spark):
    with pytest.raises(ValueError):
        rounds.reciprocal_rounds(spark.createDataFrame([], "i long, j long, d double"), spark.range(0).select("id", F.lit(1.0).alias("n")), "upgmc")


def test_forest_has_the_heights_of_single_linkage(spark):
    x = np.random.default_rng(4).normal(size=(10, 2))
    d = agg.point_matrix(x)
    got = sorted(round(r.d, 8) for r in rounds.single_by_forest(frame(spark, d)).collect())
    assert got == sorted(round(h, 8) for *_, h in agg.greedy_scan(d, np.ones(10), "single"))


def test_pairs_within_eps(spark):
    x = np.random.default_rng(5).random((60, 2)) * 10
    points = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>")
    got = {(r.i, r.j) for r in rounds.pairs_within_eps(points, 2, 1.5).collect()}
    d = agg.point_matrix(x)
    assert got == {(i, j) for i in range(60) for j in range(i + 1, 60) if d[i, j] <= 1.5}
