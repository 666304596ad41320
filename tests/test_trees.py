"""The tree, compression, validity of combinations, and hierarchies as DataFrames."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from aggclust.functions import cfdist
from aggclust.operators import compress as comp
from aggclust.operators import hierarchy as hier
from aggclust.operators import quality
from aggclust.operators.cftree import CFTree
from aggclust.plans import pipeline as pl
from aggclust.plans import workloads as wl


def blobs(n=600, d=3, seed=0):
    r = np.random.default_rng(seed)
    return r.normal(size=(n, d)) + r.integers(0, 5, (n, 1)) * 10


def frame(spark, x):
    return spark.createDataFrame([(i, v.tolist(), 1.0) for i, v in enumerate(x)], "id long, vec array<double>, w double")


def whole(n, mu, sse):
    m = (n[:, None] * mu).sum(0) / n.sum()
    return n.sum(), m, sse.sum() + (n * ((mu - m) ** 2).sum(1)).sum()


@pytest.mark.parametrize("kind", cfdist.KINDS)
def test_tree_keeps_mass_mean_and_spread(kind):
    x = blobs()
    t = CFTree(3, max_leaves=60, route=kind, width=6)
    t.insert_points(x)
    n, mu, sse = t.leaves()
    w, m, s = whole(n, mu, sse)
    assert w == 600 and len(n) == t.entries <= 60 and t.rebuilds > 0
    assert m == pytest.approx(x.mean(0)) and s == pytest.approx(((x - x.mean(0)) ** 2).sum())
    for level in {r[2] for r in t.levels()}:
        assert sum(r[4] for r in t.levels() if r[2] == level) == pytest.approx(600)


def test_radius_stays_within_the_threshold():
    t = CFTree(3, max_leaves=40, route="D0", absorb="R", width=8)
    t.insert_points(blobs())
    n, _, sse = t.leaves()
    assert np.sqrt(sse / n).max() <= t.threshold * (1 + 1e-9)


def test_threshold_zero_keeps_every_distinct_point_and_order_decides_the_tree():
    x = blobs(200)
    a, b = CFTree(3), CFTree(3)
    a.insert_points(x)
    b.insert_points(x)
    assert a.entries == 200 and all((p == q).all() for p, q in zip(a.leaves(), b.leaves()))


@pytest.mark.parametrize("growth", ["median", "mean", "double"])
def test_growth_rules(growth):
    t = CFTree(3, max_leaves=30, width=6, growth=growth)
    t.insert_points(blobs(300))
    assert t.entries <= 30 and t.threshold > 0


def test_distances_equal_pair_sums():
    r = np.random.default_rng(2)
    a, b = r.normal(size=(7, 3)), r.normal(size=(5, 3)) + 1
    u = np.vstack([a, b])
    feat = lambda p: (float(len(p)), p.mean(0), float(((p - p.mean(0)) ** 2).sum()))
    pairs = lambda p, q: ((p[:, None] - q[None]) ** 2).sum(-1)
    spread = lambda p: float(((p - p.mean(0)) ** 2).sum())
    want = {
        "D0": ((a.mean(0) - b.mean(0)) ** 2).sum(), "D1": np.abs(a.mean(0) - b.mean(0)).sum() ** 2, "D2": pairs(a, b).mean(),
        "D3": pairs(u, u).sum() / (12 * 11), "D4": spread(u) - spread(a) - spread(b), "R": spread(u) / 12,
    }
    (n, m, s), (k, c, t) = feat(a), feat(b)
    for kind, value in want.items():
        got = cfdist.squared_to_many(kind, n, m, s, np.array([k]), c[:, None], np.array([t]))[0]
        assert got == pytest.approx(value)


def test_compress_in_rounds(spark):
    x = blobs(900)
    p = frame(spark, x)
    for options in ({"partitions": 1}, {"partitions": 7, "fan_in": 3}, {"partitions": 3, "dedupe": True}, {"partitions": 2, "grid": 0.5}, {"order": "scan", "fan_in": 2}):
        rows = comp.compress(p, 3, max_leaves=80, **options).collect()
        n, mu, sse = np.array([r.n for r in rows]), np.array([r.mu for r in rows]), np.array([r.sse for r in rows])
        w, m, s = whole(n, mu, sse)
        assert w == 900 and len(rows) <= 80 and [r.cf_id for r in rows] == list(range(len(rows)))
        assert m == pytest.approx(x.mean(0)) and s == pytest.approx(((x - x.mean(0)) ** 2).sum())
    again = comp.compress(p.repartition(5), 3, max_leaves=80, partitions=7, fan_in=3).collect()
    assert again == comp.compress(p, 3, max_leaves=80, partitions=7, fan_in=3).collect()
    assert comp.compress(p.limit(0), 3, partitions=2).count() == 0


def test_combinations_without_meaning_are_refused():
    for bad in (("full", "none", "ward", None), ("cf_linkage", "cached", "single", None), ("cf_linkage", "chain_linear", "wpgmc", None), ("full", "chain_linear", "complete", None), ("cf_aggregation", "cached", None, "D9"), ("full", "chain_linear", "upgma", None)):
        with pytest.raises(ValueError):
            pl.validate(*bad)


def test_no_compression_gives_the_full_result(spark):
    x = blobs(120)
    p = frame(spark, x)
    want = None
    for mode, search in (("full", "scan"), ("cf_centers", "cached"), ("cf_linkage", "cached"), ("cf_linkage", "chain_linear")):
        items, merges = pl.cluster(p, 3, mode, search, "ward", max_leaves=1000, partitions=1)
        heights = sorted(round(r.height, 6) for r in merges.collect())
        want = want or heights
        assert heights == want
    got = quality.rmsd(hier.cluster_cfs(items, hier.cut_k(merges, 5), 3)).first()
    labels = {r.item: r.cluster for r in hier.cut_k(merges, 5).collect()}
    mus = {r.cf_id: r.mu for r in items.collect()}
    assert got.rmsd == pytest.approx(wl.brute_rmsd(np.array([mus[i] for i in range(120)]), np.array([labels[i] for i in range(120)])))
    assert got.k == 5


def test_cuts_and_labels(spark):
    x = blobs(60)
    p = frame(spark, x)
    items, merges = pl.cluster(p, 3, "full", "chain_linear", "ward")
    merges = merges.cache()
    top = merges.agg(F.max("height")).first()[0]
    assert hier.cut_height(merges, top).select("cluster").distinct().count() == 1
    assert hier.cut_height(merges, -1.0).select("cluster").distinct().count() == 60
    sizes = {r.k: r.c for r in hier.sweep_k(merges, [1, 4, 60]).groupBy("k").agg(F.countDistinct("cluster").alias("c")).collect()}
    assert sizes == {1: 1, 4: 4, 60: 60}
    assert hier.members(merges, 118).count() == 60 and hier.inversions(merges).count() == 0
    assert hier.cophenetic(merges).count() == 60 * 59 // 2
    near = comp.assign_to_leaves(p, items)
    assert near.where("id = cf_id").count() == 60
    assert quality.adjusted_rand(spark.createDataFrame([(1, 1), (1, 1), (2, 2)], "a int, b int"), "a", "b").first().ari == 1.0


def test_the_limit_of_one_task_is_enforced(spark):
    p = pl.as_items(frame(spark, blobs(30)))
    with pytest.raises(Exception, match="compress first"):
        pl.hierarchy(p, "full", "cached", "ward", limit=10).collect()


def one_by_one(x, cap, width, kind, growth="mean"):
    """Insertion of one point after the other, as plain lists: the tree that blocks of one must give."""
    t = CFTree(x.shape[1], max_leaves=cap, width=width, route=kind, growth=growth, block=1)
    t.insert_points(x)
    return t


@pytest.mark.parametrize("kind", ["D0", "D4", "R"])
def test_blocks_keep_the_invariants_of_single_insertion(kind):
    x = blobs(3000, seed=3)
    single = one_by_one(x, 300, 8, kind)
    blocks = CFTree(3, max_leaves=300, width=8, route=kind)
    blocks.insert_points(x)
    for t in (single, blocks):
        n, mu, sse = t.leaves()
        w, m, s = whole(n, mu, sse)
        assert w == 3000 and t.entries <= 300 and m == pytest.approx(x.mean(0)) and s == pytest.approx(((x - x.mean(0)) ** 2).sum())
        if kind == "R":
            assert np.sqrt(sse / n).max() <= t.threshold * (1 + 1e-9)
    # The radius takes whole blobs as one once its threshold reaches their gaps, in either way of inserting.
    assert kind == "R" or 0.3 < single.entries / blocks.entries < 3


def test_every_node_knows_its_children():
    t = CFTree(3, max_leaves=500, width=5)
    t.insert_points(blobs(2500, seed=4))
    rows = t.levels()
    below = {}
    for me, parent, *_ in rows[1:]:
        below.setdefault(parent, []).append(me)
    at = {r[0]: r for r in rows}
    for parent, kids in below.items():
        n, mu, sse = (np.array([at[k][c] for k in kids]) for c in (4, 5, 6))
        w, m, s = whole(n, mu, sse)
        assert at[parent][4] == pytest.approx(w) and at[parent][5] == pytest.approx(m) and at[parent][6] == pytest.approx(s)
        assert len(kids) <= 5
    assert len({r[2] for r in rows if r[3]}) == 1  # all entries on one level


def test_searches_run_as_they_are_named():
    """At 7000 items, above every earlier switch: a matrix search fills a matrix, a linear one none."""
    from aggclust.operators.agglomerate import Counters

    r = np.random.default_rng(0)
    x = r.random((7000, 5)) * 100
    tops = []
    for search, cells in (("cached", 7000 * 6999 // 2), ("chain_linear", 0), ("cached_linear", 0)):
        c = Counters()
        merges = pl.solve(np.ones(7000), x, np.zeros(7000), "full", search, "ward", counters=c)
        assert c.cells == cells
        tops.append(sorted(m[4] for m in merges)[-20:])
    assert tops[0] == pytest.approx(tops[1]) and tops[0] == pytest.approx(tops[2])


def test_runs_in_memory_and_by_operators_agree(spark):
    """The grid's runs and the operators' give the same measure for the same points; counters reach the record."""
    x = blobs(150)
    p = frame(spark, x)
    for search, mode in (("cached", "full"), ("chain_linear", "full"), ("chain_linear", "cf_linkage")):
        a = wl.solved(x, np.ones(150), search, mode, "ward", 6, 1000, 0)
        b = wl.run(p, 3, search, mode, "ward", 6, 1000)
        assert a["rmsd"] == pytest.approx(b["rmsd"]) and a["leaves"] == b["leaves"] == 150
        assert b["distances"] > 0 and b["peak_bytes"] > 0 and (b["cells"] > 0) == (search == "cached")
    assert wl.chosen("cached", "full", 50_000) == "cached_linear" and wl.chosen("cached", "cf_linkage", 25_000) == "cached"


def test_labels_without_broadcast(spark, monkeypatch):
    monkeypatch.setattr(hier, "CAP", 3)
    assigned = spark.createDataFrame([(i, i % 5) for i in range(20)], "id long, cf_id long")
    labels = spark.createDataFrame([(i, i // 2) for i in range(5)], "item long, cluster long")
    assert {r.id: r.cluster for r in hier.label_points(assigned, labels).collect()} == {i: i % 5 // 2 for i in range(20)}


def test_strategies_of_merging_agree(spark):
    """By two passes, by Arrow batches first, and one after the other; keys may be null."""
    from aggclust.functions import features as ft

    r = np.random.default_rng(1)
    rows = [(int(k) if k else None, "ab"[int(k) % 2], (float(n), [float(v) for v in m], float(s))) for k, n, m, s in zip(r.integers(0, 5, 200), r.integers(1, 9, 200), r.normal(size=(200, 2)) + 1e6, r.random(200))]
    df = spark.createDataFrame(rows, "k int, t string, cf struct<n:double,mu:array<double>,sse:double>").repartition(3)
    for keys in (["k", "t"], []):
        found = [sorted(((str([x[c] for c in keys]), x.cf.n, *x.cf.mu, x.cf.sse) for x in ft.cf_merge_agg(df, keys, 2, strategy=s).collect())) for s in ("twopass", "arrow", "fold")]
        for other in found[1:]:
            assert [x[0] for x in other] == [x[0] for x in found[0]]
            assert [x[1:] for x in other] == [pytest.approx(x[1:], rel=1e-6) for x in found[0]]
