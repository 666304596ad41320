"""Queries use every row of their tables, and blocks of pairs equal brute force."""

import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from aggclust.functions import linkage as link
from aggclust.operators import blocks
from aggclust.plans import workloads
from aggclust.queries import basics, surround


def points(spark, n=200, d=3, copies=20):
    x = np.random.default_rng(5).normal(size=(n, d))
    x[:copies] = x[0]
    df = spark.createDataFrame([(i, i % 4, x[i].tolist()) for i in range(n)], "id long, g long, v array<double>")
    return x, np.sqrt(((x[:, None] - x[None]) ** 2).sum(-1)), df


@pytest.mark.parametrize("name,squared", [("single", False), ("complete", False), ("upgma", False), ("upgma", True), ("upgmc", False), ("ward", False)])
def test_linkages_use_every_row(spark, tmp_path, name, squared):
    rows = [(i, float((i * 7919) % 1009)) for i in range(300)]
    spark.createDataFrame(rows, "c_custkey long, c_acctbal double").write.parquet(f"{tmp_path}/customer.parquet")
    x = {g: np.array([(b / 1000, k / 1000) for k, b in rows if k % 6 == g]) for g in range(6)}
    q = "link_" + name + ("_sq" if squared else "")
    got = {(r.a, r.b): r.d for r in basics.QUERIES[q](spark, str(tmp_path)).collect()}
    assert len(got) == 15
    for (a, b), d in got.items():
        assert d == pytest.approx(link.closed_form(name, x[a], x[b], squared), abs=2e-6)


@pytest.mark.parametrize("name", ["single", "complete", "upgma"])
def test_linkage_over_many_tiles(spark, name, monkeypatch):
    monkeypatch.setattr(blocks.block_pairs, "__defaults__", (48,))
    x, _, df = points(spark)
    g = np.arange(len(x)) % 4
    for r in link.linkage_between(df.select("g", "v"), "g", "v", name).collect():
        assert r.d == pytest.approx(link.closed_form(name, x[g == r.a], x[g == r.b]))


def test_event_features_cover_every_user(spark, tmp_path):
    rows = [(u * 10 + i, u, f"2024-01-01 {i * 3:02d}:00:00", float(i)) for u in (1, 25, 500) for i in range(5)]
    e = spark.createDataFrame(rows, "event_id long, user_id long, ts string, value double")
    e.withColumn("ts", F.col("ts").cast("timestamp_ntz")).write.parquet(f"{tmp_path}/events.parquet")
    for q in ("running_cf", "sliding_cf", "asof_event"):
        assert {r.event_id for r in surround.QUERIES[q](spark, str(tmp_path)).collect()} == {r[0] for r in rows}
    # Three hours apart, every event is a session of its own.
    assert sorted(r.user_id for r in surround.QUERIES["cf_session"](spark, str(tmp_path)).collect()) == sorted(r[1] for r in rows)


@pytest.mark.parametrize("tile", [48, 4096])
def test_vector_queries_use_every_row(spark, tmp_path, tile, monkeypatch):
    monkeypatch.setattr(blocks.block_pairs, "__defaults__", (tile,))
    x, _, _ = points(spark, 450, 8)
    x = x.astype(np.float32).astype(float)
    dist = np.sqrt(((x[:, None] - x[None]) ** 2).sum(-1))
    spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    run = lambda q: surround.QUERIES[q](spark, str(tmp_path)).collect()
    every = sorted((dist[i, j], i, j) for i in range(450) for j in range(i + 1, 450))
    got = run("pairwise_embeddings")[0]
    assert (got.pairs, got.low) == (len(every), 0.0) and got["mean"] == pytest.approx(np.mean([d for d, *_ in every]), abs=1e-5)
    assert [(r.i, r.j) for r in run("closest_pairs")] == [(i, j) for _, i, j in every[:20]]
    order = [sorted((dist[i, j], j) for j in range(450) if j != i) for i in range(450)]
    assert {r.u: r.v for r in run("nearest_neighbour")} == {i: o[0][1] for i, o in enumerate(order)}
    assert {(r.i, r.rank): r.j for r in run("knn_rank")} == {(i, k + 1): o[k][1] for i, o in enumerate(order) for k in range(3)}


def lines_by_flag(spark, folder):
    """The known triple (0, 1), (0, -1), (4, 0) as means of two, three and four lines of a supplier; another lacks a flag."""
    rows = [(7, f, 10.0 + x + e, (10.0 + y) * 2085) for f, n, x, y in (("A", 2, 0, 1), ("N", 3, 0, -1), ("R", 4, 4, 0)) for e in np.linspace(-1, 1, n).tolist()]
    rows += [(8, "A", 1.0, 1.0), (8, "N", 2.0, 2.0)]
    spark.createDataFrame(rows, "l_suppkey long, l_returnflag string, l_quantity double, l_extendedprice double").write.parquet(f"{folder}/lineitem.parquet")


def test_coefficients_of_given_sizes(spark, tmp_path):
    lines_by_flag(spark, tmp_path)
    got = {r.linkage: (r.alpha_a, r.alpha_b, r.beta, r.gamma) for r in basics.QUERIES["coefficients"](spark, str(tmp_path)).collect() if r.k == 7}
    assert set(got) == set(link.LINKAGES)
    for name, values in got.items():
        assert values == pytest.approx(link.coefficients(name, 2.0, 3.0, 4.0), abs=1e-6)


def test_last_height_depends_on_the_first_pair(spark, tmp_path):
    lines_by_flag(spark, tmp_path)
    far = 17**0.5
    got = {(r.k, r.first): r.d for r in basics.QUERIES["wpgma_history"](spark, str(tmp_path)).collect()}
    assert got == pytest.approx({(7, "ab"): far, (7, "ac"): (2 + far) / 2, (7, "bc"): (2 + far) / 2}, abs=1e-6)


def test_inversion_of_given_means(spark, tmp_path):
    lines_by_flag(spark, tmp_path)
    got = [tuple(r) for r in basics.QUERIES["inversion_demo"](spark, str(tmp_path)).collect()]
    assert len(got) == 1 and got[0][:4] == pytest.approx((7, 4.0, 17.0, 16.0), abs=1e-6) and got[0][4] is True


def test_exploration_uses_whole_tables(spark):
    sf = "/root/testdata/sf0.001"
    if not os.path.isdir(sf):
        pytest.skip("the given tables are not here")
    t = lambda name: spark.read.parquet(f"{sf}/{name}.parquet")
    want = {"suppliers": "supplier", "parts": "part", "pages": "pages", "embeddings": "embeddings", "documents": "documents"}
    want = {k: t(v).count() for k, v in want.items()}
    want |= {"nations": t("customer").select("c_nationkey").distinct().count(), "users": t("events").select("user_id").distinct().count(), "conversations": t("conversations").select("conv_id").distinct().count()}
    assert {r.table: r.points for r in workloads.exploration(spark, sf, partitions=2).collect()} == want
