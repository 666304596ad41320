"""Agglomeration kernels against each other and against definitions."""

import numpy as np
import pytest

from aggclust.functions import linkage as link
from aggclust.functions.cfdist import KINDS, NOT_REDUCIBLE, squared_matrix
from aggclust.operators import agglomerate as agg

NAMES = list(link.LINKAGES)


def points(n=40, d=3, seed=0):
    return np.random.default_rng(seed).normal(size=(n, d))


def features(n=40, d=3, seed=1):
    r = np.random.default_rng(seed)
    return r.integers(1, 9, n).astype(float), r.normal(size=(n, d)), r.random(n)


def tree(merges, m):
    """Member sets with heights, independent of order and numbering."""
    own = {i: frozenset([i]) for i in range(m)}
    out = {}
    for _, left, right, node, h, _ in agg.number(merges, np.ones(m), "height"):
        own[node] = own[left] | own[right]
        out[own[node]] = round(h, 9)
    return out


@pytest.mark.parametrize("name", NAMES)
def test_recurrence_is_the_closed_form(name):
    if name in ("wpgma", "wpgmc"):
        with pytest.raises(ValueError):
            link.closed_form(name, points(3), points(2))
        return
    a, b, c = points(4, seed=1), points(5, seed=2), points(3, seed=3)
    for squared in (False, True) if name == "upgma" else (False,):
        d = [link.closed_form(name, x, y, squared) for x, y in ((a, c), (b, c), (a, b))]
        got = link.recur(name, *d, 4.0, 5.0, 3.0)
        assert got == pytest.approx(link.closed_form(name, np.vstack([a, b]), c, squared))


@pytest.mark.parametrize("name", NAMES)
def test_cached_greedy_equals_scan_and_chains_equal_greedy_where_reducible(name):
    x = points(50)
    d = agg.point_matrix(x, squared=link.get(name).squared)
    scan = agg.greedy_scan(d, np.ones(50), name)
    assert agg.greedy_cached(d, np.ones(50), name) == scan
    chain = agg.chain_matrix(d, np.ones(50), name)
    assert len(chain) == 49
    if link.get(name).reducible:
        assert tree(chain, 50) == tree(scan, 50)


@pytest.mark.parametrize("kind", KINDS)
def test_aggregation_searches_agree(kind):
    f = features()
    scan = agg.agglomerate_cf(*f, kind, "scan")
    assert tree(agg.agglomerate_cf(*f, kind, "cached"), 40) == tree(scan, 40)
    for search in ("chain_matrix", "chain_linear"):
        got = agg.agglomerate_cf(*f, kind, search)
        assert len(got) == 39
        if kind not in NOT_REDUCIBLE:
            assert tree(got, 40) == tree(scan, 40)


@pytest.mark.parametrize("name,kind,factor", [("upgmc", "D0", 1), ("upgma", "D2", 1), ("ward", "D4", 2)])
def test_recurrence_on_seeded_features_equals_aggregation(name, kind, factor):
    n, mu, sse = features(60)
    d = squared_matrix(kind, n, mu, sse) * factor
    by_recurrence = tree(agg.greedy_scan(d, n, name), 60)
    by_features = {k: round(h * factor, 9) for k, h in tree(agg.agglomerate_cf(n, mu, sse, kind, "scan"), 60).items()}
    assert by_recurrence.keys() == by_features.keys()
    assert all(by_recurrence[k] == pytest.approx(by_features[k]) for k in by_recurrence)


def test_ties_go_to_the_smallest_slots():
    x = np.array([[0.0], [1.0], [2.0], [3.0]])
    for run in (agg.greedy_scan, agg.greedy_cached):
        assert [m[:2] for m in run(agg.point_matrix(x), np.ones(4), "single")] == [(0, 1), (0, 2), (0, 3)]
    assert [m[:2] for m in agg.greedy_linear(np.ones(4), x, np.zeros(4), "D4")][:2] == [(0, 1), (2, 3)]


def test_inversion_of_the_centroid_linkage():
    x = np.array([[0.0, 1.0], [0.0, -1.0], [4.0, 0.0]])
    # Moved apart so that the pair merges first: 17 to either, 16 to the union.
    heights = [h for *_, h in agg.greedy_scan(agg.point_matrix(x, squared=True), np.ones(3), "upgmc")]
    assert heights == pytest.approx([4.0, 16.0])


def test_numbering_never_puts_a_merge_before_its_parts():
    n, mu, sse = features(80, seed=5)
    for search in ("scan", "chain_matrix"):
        rows = agg.number(agg.agglomerate_cf(n, mu, sse, "D0", search), n)
        seen = set(range(80))
        for _, left, right, node, _, _ in rows:
            assert left in seen and right in seen
            seen.add(node)
        assert rows[-1][5] == pytest.approx(n.sum())


def test_cut_labels():
    x = np.array([[0.0], [0.1], [5.0], [5.1], [9.0]])
    rows = agg.number(agg.greedy_scan(agg.point_matrix(x), np.ones(5), "single"), np.ones(5))
    assert agg.cut(rows, 5, 3).tolist() == [0, 0, 2, 2, 4]
    assert agg.cut(rows, 5, 1).tolist() == [0] * 5 and agg.cut(rows, 5, 9).tolist() == [0, 1, 2, 3, 4]


def brute_chain(m, distance, merge):
    """The chain in plain loops: distance(i, j) of live clusters, merge(i, j) into i."""
    alive, path, out = set(range(m)), [], []
    while len(out) < m - 1:
        if not path:
            path = [min(alive)]
        i = path[-1]
        best = min((distance(min(i, j), max(i, j)), j) for j in alive if j != i)
        j = best[1]
        if len(path) > 1 and distance(min(i, path[-2]), max(i, path[-2])) <= best[0]:
            j = path[-2]
        if len(path) > 1 and j == path[-2]:
            del path[-2:]
        elif j in path:
            path = []
        else:
            path.append(j)
            continue
        a, b = min(i, j), max(i, j)
        out.append((a, b, distance(a, b)))
        merge(a, b)
        alive.discard(b)
    return out


@pytest.mark.parametrize("kind", KINDS)
def test_chains_of_features_equal_plain_loops(kind):
    """Also for distances that are not reducible, where a chain's result is its own."""
    from aggclust.functions.cfdist import squared_to_many

    n, mu, sse = features(30, seed=4)
    live = [[n[i], mu[i].copy(), sse[i]] for i in range(30)]

    def distance(i, j):
        (a, x, s), (b, y, t) = live[i], live[j]
        return float(squared_to_many(kind, a, x, s, np.array([b]), y[:, None], np.array([t]))[0])

    def merge(i, j):
        (a, x, s), (b, y, t) = live[i], live[j]
        gap = y - x
        live[i] = [a + b, x + gap * (b / (a + b)), s + t + a * b / (a + b) * float(gap @ gap)]

    want = brute_chain(30, distance, merge)
    for search in ("chain_linear", "chain_matrix"):
        got = agg.agglomerate_cf(n, mu, sse, kind, search)
        assert [(i, j) for i, j, _ in got] == [(i, j) for i, j, _ in want]
        assert [h for *_, h in got] == pytest.approx([h for *_, h in want])


@pytest.mark.parametrize("name", ["upgmc", "wpgmc", "ward", "upgma"])
def test_chains_of_matrices_equal_plain_loops(name):
    d = agg.point_matrix(points(30, seed=6), squared=True)
    size, live = np.ones(30), d.copy()

    def merge(i, j):
        live[i] = live[:, i] = link.recur(name, live[i], live[j], live[i, j], size[i], size[j], size)
        size[i] += size[j]

    want = brute_chain(30, lambda i, j: float(live[i, j]), merge)
    got = agg.chain_matrix(d, np.ones(30), name)
    assert [m[:2] for m in got] == [m[:2] for m in want] and [m[2] for m in got] == pytest.approx([m[2] for m in want])


@pytest.mark.parametrize("name,kind,factor", [("ward", "D4", 2), ("upgmc", "D0", 1)])
@pytest.mark.parametrize("shift", [0.0, 1e6])
def test_the_centres_chain_is_the_chain_of_features(name, kind, factor, shift):
    n, mu, _ = features(400, seed=8)
    got = agg.chain_centres(n, mu + shift, name)
    want = agg.chain_linear(n, mu + shift, np.zeros(400), kind)
    assert [m[:2] for m in got] == [m[:2] for m in want]
    assert [m[2] for m in got] == pytest.approx([m[2] * factor for m in want], rel=1e-5)


@pytest.mark.parametrize("name,kind", [("ward", "D4"), ("upgmc", "D0")])
@pytest.mark.parametrize("weighted", [False, True])
def test_the_centres_greedy_is_the_scan(name, kind, weighted):
    n, mu, _ = features(250, seed=11)
    n = n if weighted else np.ones(250)
    d = squared_matrix(kind, n, mu, np.zeros(250)) * link.get(name).cf_factor
    got, want = agg.greedy_centres(n, mu + 1e4, name), agg.greedy_scan(d, n, name)
    assert [m[:2] for m in got] == [m[:2] for m in want] and [m[2] for m in got] == pytest.approx([m[2] for m in want])
    grid = np.array([[i, j] for i in range(6) for j in range(6)], float)  # ties everywhere
    got = agg.greedy_centres(np.ones(36), grid, name)
    assert len(got) == 35 and got[0][:2] == (0, 1) and len({m[1] for m in got}) == 35


@pytest.mark.parametrize("name", NAMES)
def test_condensed_matrices_compact_and_agree(name):
    x = points(300, seed=7)
    d = agg.point_matrix(x, squared=link.get(name).squared)
    want = agg.greedy_scan(d, np.ones(300), name)
    got = agg.greedy_cached(agg.condensed_points(x, squared=link.get(name).squared), np.ones(300), name)
    assert [m[:2] for m in got] == [m[:2] for m in want] and [m[2] for m in got] == pytest.approx([m[2] for m in want])


def test_a_matrix_beyond_its_limit_raises(monkeypatch):
    monkeypatch.setattr(agg, "MATRIX_BYTES", 10_000)
    for make in (lambda: agg.Condensed(60), lambda: agg.point_matrix(points(40)), lambda: agg.agglomerate_cf(*features(40), "D4", "scan")):
        with pytest.raises(ValueError, match="compress first"):
            make()
    assert 4 * 25_000 * 24_999 < 3e9


@pytest.mark.parametrize("name", link.BY_DEFINITION)
def test_linkages_by_definition_equal_plain_loops(name):
    x = points(14, seed=9)
    d = agg.point_matrix(x)
    own = np.where(np.isinf(d), 0.0, d)
    live = {i: [i] for i in range(14)}

    def value(a, b):
        if name == "minimax":
            return min(max(own[i][j] for j in a + b) for i in a + b)
        centre = [min(m, key=lambda i: (sum(own[i][j] for j in m), i)) for m in (a, b)]
        return own[centre[0]][centre[1]]

    for i, j, h in agg.greedy_definition(d, name):
        best = min((value(sorted(live[p]), sorted(live[q])), p, q) for p in live for q in live if p < q)
        assert (i, j) == best[1:] and h == pytest.approx(best[0])
        live[i] += live.pop(j)


def test_jaccard_distance_of_sets():
    sets = [{1, 2, 3}, {2, 3, 4}, {5}, set()]
    x = np.array([[float(k in s) for k in range(6)] for s in sets])
    d = agg.point_matrix(x, "jaccard")
    for i in range(4):
        for j in range(4):
            if i != j:
                both = sets[i] | sets[j]
                assert d[i, j] == pytest.approx(1 - (len(sets[i] & sets[j]) / len(both) if both else 1))


@pytest.mark.parametrize("metric", ["jaccard", "manhattan"])
@pytest.mark.parametrize("last", [1, 40, 5_657])
def test_complete_linkage_in_linear_memory_equals_the_matrix(metric, last, monkeypatch):
    monkeypatch.setattr(agg, "LAST_MATRIX", last)
    for mean, scale in ((0.5, 1.0), (4.0, 1.0), (15.0, 0.25)):
        x = np.random.default_rng(3).poisson(mean, (250, 5)) * scale
        x[200:] = x[:50]
        want = agg.greedy_cached(agg.condensed_points(x, metric), np.ones(250), "complete")
        assert agg.complete_linear(x, metric) == want


def test_jaccard_hierarchy_of_more_users_than_a_matrix_takes(spark, tmp_path, monkeypatch):
    from aggclust.plans import pipeline as pl
    from aggclust.queries import experiments

    kinds, n = "abcde", 120
    x = np.random.default_rng(4).poisson(2, (n, 5))
    x[:, 0] += 1
    rows = [(u, kinds[k]) for u in range(n) for k in range(5) for _ in range(x[u, k])]
    spark.createDataFrame(rows, "user_id long, event_type string").write.parquet(f"{tmp_path}/events.parquet")
    want = pl.solve(np.ones(n), x.astype(float), np.zeros(n), "full", "cached", "complete", base="jaccard")
    # Limits that these users break, as 90,000 break the true ones.
    monkeypatch.setattr(pl, "FULL_LIMIT", 50)
    for f in (pl.hierarchy, pl.counted):
        monkeypatch.setattr(f, "__defaults__", (*f.__defaults__[:-1], 50))
    got = experiments.agg_full_jaccard(spark, str(tmp_path)).orderBy("step").collect()
    assert [(r.step, r.a, r.b, r["size"]) for r in got] == [(s, min(a, b), max(a, b), z) for s, a, b, _, _, z in want]
    assert [r.height for r in got] == pytest.approx([h for *_, h, _ in want], abs=1e-6)


def test_counters():
    n, mu, sse = features(50)
    for run, cells in ((lambda c: agg.chain_centres(n, mu, "ward", c), 0), (lambda c: agg.greedy_cached(agg.condensed_features("D4", n, mu, sse), n, "ward", c), 50 * 49 // 2)):
        c = agg.Counters()
        run(c)
        assert c.distances > 0 and c.cells == cells and c.peak_bytes > 0
