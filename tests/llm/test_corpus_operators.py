"""Fingerprints, near duplicates, embeddings, sharding, mixing and the pipeline against brute force."""

import collections
import hashlib
import itertools
import math
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from aggclust.llm import components, embeddings, fingerprints, mixing, near_duplicates, sharding
from aggclust.llm.shingles import shingles


def test_fingerprints_of_edits_and_neighbours(spark):
    r = random.Random(1)
    t = [" ".join(r.choice(["alpha", "beta", "gamma", "delta", "eps", "zeta\n", "eta"]) + str(r.randint(0, 30)) for _ in range(r.randint(0, 400))) for _ in range(120)] + ["", None, "x"]
    ids = r.sample(range(1000), len(t))
    docs = spark.createDataFrame([(i, x, 1, "f") for i, x in zip(ids, t)], "doc_id long, text string, bin int, fingerprint string")
    got = [x for x in sorted(fingerprints.with_next(docs, bins=7).collect(), key=lambda x: -x.doc_id)]
    order = sorted(zip(ids, t), reverse=True)
    text = [x or "" for _, x in order]

    def sets(x):
        owner, digest = fingerprints.paragraphs(x)
        out = [set() for _ in x]
        for o, d in zip(owner.tolist(), digest.tolist()):
            out[o].add(d)
        return out

    edited = [fingerprints.edit(a, b) for a, b in zip(text, text[1:] + text[:1])]
    own, new = sets(text), sets(edited)
    like = lambda a, b: len(a & b) / len(a | b) if a | b else 1.0
    assert [x.doc_id for x in got] == [i for i, _ in order]
    assert [x.n_chars for x in got] == [len(x) for x in text]
    assert [x.edited_sha256 for x in got] == [hashlib.sha256(e.encode()).hexdigest() for e in edited]
    assert [x.near_edited for x in got] == pytest.approx([like(a, b) for a, b in zip(own, new)])
    assert [x.near_next for x in got] == pytest.approx([like(a, b) for a, b in zip(own, own[1:] + own[:1])])
    plain = {x.doc_id: x.fingerprint for x in fingerprints.fingerprint(docs).collect()}
    assert all(plain[x.doc_id] == x.fingerprint for x in got)
    assert fingerprints.with_next(docs.limit(0)).count() == 0


def test_fingerprints_of_ties_and_nulls(spark):
    docs = spark.createDataFrame([(1, "a b"), (None, None), (1, "a b"), (3, "")], "doc_id long, text string")
    got = sorted((x.doc_id if x.doc_id is not None else -1, x.near_next) for x in fingerprints.with_next(docs).collect())
    assert got == [(-1, 1.0), (1, 0.0), (1, 1.0), (3, 0.0)]


def test_peeling_counts_differences_of_any_size():
    r = np.random.default_rng(0)
    a, b = [], []
    for k in (0, 1, 5, 40, 900):
        base = r.integers(1, 2**63, 300).astype(np.uint64)
        a.append(np.unique(np.concatenate([base, r.integers(1, 2**63, k).astype(np.uint64)])))
        b.append(np.unique(np.concatenate([base, r.integers(1, 2**63, 2 * k).astype(np.uint64)])))
    pack = lambda s: (np.repeat(np.arange(len(s)), [len(x) for x in s]), np.concatenate(s))
    stored = fingerprints.sketched(pack(a), 5), fingerprints.sketched(pack(b), 5)
    for given in (None, stored):
        only_a, only_b = fingerprints.differences(pack(a), pack(b), 5, given)
        assert only_a.tolist() == [0, 1, 5, 40, 900] and only_b.tolist() == [0, 2, 10, 80, 1800]


def test_stored_fingerprints_subtract_and_peel(spark):
    """What two stored strings recover is what the sets of digests differ by; the query's likeness is theirs."""
    r = random.Random(2)
    words = [f"w{i}" for i in range(500)]
    base = [" ".join(r.choice(words) for _ in range(300)) for _ in range(30)]
    other = [" ".join(w if r.random() > 0.01 * (i % 4) else "new" for w in x.split()) for i, x in enumerate(base)]
    one, two = (fingerprints.fingerprints(t, fingerprints.paragraphs(t)) for t in (base, other))
    done = 0
    for x, y, a, b in zip(base, other, one, two):
        p, q = (set(fingerprints.paragraphs([t])[1].tolist()) for t in (x, y))
        got = fingerprints.compare(a, b)
        if got is not None:
            done += 1
            assert (set(got[0]), set(got[1])) == (p - q, q - p) and got[2] == pytest.approx(len(p & q) / len(p | q))
    assert done >= 20 and fingerprints.compare(one[0], two[1]) is None
    docs = spark.createDataFrame(list(enumerate(base)), "doc_id long, text string")
    near = {x.doc_id: x for x in fingerprints.with_next(docs).collect()}
    again = [(x.near_edited, fingerprints.compare(x.fingerprint, x.edited_fingerprint)) for x in near.values()]
    assert all(c is None or c[2] == pytest.approx(n) for n, c in again)
    pairs = spark.createDataFrame([(i, x, y) for i, (x, y) in enumerate(zip(base, other[1:] + [None]))], "id long, a string, b string")
    for x in fingerprints.changed(pairs, "id", "a", "b").collect():
        p, q = (set(fingerprints.paragraphs([t])[1].view(np.int64).tolist()) for t in (base[x.id], (other[1:] + [""])[x.id]))
        assert (set(x.removed), set(x.added)) == (p - q, q - p)


def test_shingles():
    owner, digest, n = shingles(["A b c d e f", "a B, c d e", "", "one", "one two", "!!!", "a b c d e f g h a b c d e f g h"])
    assert owner.tolist() == [0, 0, 1, 3, 4] + [6] * 8 and sorted(n[owner == 6].tolist()) == [1, 1, 1, 1, 2, 2, 2, 2]
    assert digest[owner == 1][0] in digest[owner == 0]
    assert shingles(["one two"])[1][0] == digest[owner == 4][0]


def test_probability_jaccard_and_its_sketch():
    r = np.random.default_rng(0)
    for _ in range(100):
        ka, kb = (np.unique(r.integers(0, 30, 20)).astype(np.uint64) for _ in "ab")
        wa, wb = (r.integers(1, 5, len(k)).astype(float) for k in (ka, kb))
        a, b = dict(zip(ka, wa)), dict(zip(kb, wb))
        every = set(a) | set(b)
        want = sum(1 / sum(max(a.get(q, 0) / a[c], b.get(q, 0) / b[c]) for q in every) for c in set(a) & set(b))
        assert near_duplicates.probability_jaccard((ka, wa), (kb, wb)) == pytest.approx(want)
    key = np.sort(fingerprints.mix(np.arange(1, 101, dtype=np.uint64)))
    w = r.integers(1, 4, 100).astype(float)
    owner = np.r_[np.zeros(100, int), np.ones(80, int)]
    s = near_duplicates.probminhash(owner, np.r_[key, key[20:]], np.r_[w, w[20:]], 2, 4000)
    assert (s[0] == s[1]).mean() == pytest.approx(near_duplicates.probability_jaccard((key, w), (key[20:], w[20:])), abs=0.03)


def corpus(seed=5):
    r = random.Random(seed)
    words = ["".join(r.choice("abcdefgh") for _ in range(4)) for _ in range(400)]
    make = lambda k: [r.choice(words) for _ in range(k)]
    out = []
    for _ in range(14):
        base = make(r.randint(40, 160))
        out.append(base)
        for _ in range(r.randint(0, 8)):
            copy = list(base)
            for _ in range(r.randint(0, 6)):
                copy[r.randrange(len(copy))] = r.choice(words)
            out.append(copy)
    line = make(60)
    out += [line + make(50) for _ in range(25)]
    out += [line * 3 + make(20) for _ in range(4)]
    t = [" ".join(x) for x in out] + ["", "", None, "one two", "one two", "one three", "!!! ???"]
    r.shuffle(t)
    return t


def brute(t):
    def bag(x):
        w = re.findall(r"[0-9a-z\x80-\U0010ffff]+", x.lower())
        return collections.Counter(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else collections.Counter()

    t = [x or "" for x in t]
    bags, root = [bag(x) for x in t], list(range(len(t)))

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, j in itertools.combinations(range(len(t)), 2):
        a, b = bags[i], bags[j]
        near = t[i] == t[j]
        if not near and set(a) & set(b):
            number = {s: k for k, s in enumerate(sorted(set(a) | set(b)))}
            pack = lambda c: (np.array(sorted(number[s] for s in c), np.uint64), np.array([c[s] for s in sorted(c)], float))
            near = near_duplicates.probability_jaccard(pack(a), pack(b)) >= 0.8
        if near:
            x, y = sorted((top(i), top(j)))
            root[y] = x
    return [top(i) for i in range(len(t))]


def test_near_duplicates_equal_brute_force(spark, monkeypatch):
    monkeypatch.setattr(near_duplicates, "TILE", 8)
    t = corpus()
    docs = spark.createDataFrame([(i, x, "m") for i, x in enumerate(t)], "doc_id long, text string, mark string")
    found, links = near_duplicates.classes(docs)
    want = brute(t)
    assert {r.doc_id: r.class_id for r in found.collect()} == dict(enumerate(want))
    assert all(r.similarity >= 0.8 - 1e-9 for r in links.collect())
    kept = near_duplicates.keep_one(docs)
    assert sorted(r.doc_id for r in kept.collect()) == sorted(set(want)) and kept.columns == docs.columns


def test_near_duplicates_without_ids_and_rows(spark):
    docs = spark.createDataFrame([(None, "a b c d e f"), (None, "a b c d e f"), (7, "x"), (7, "x")], "doc_id long, text string")
    found, _ = near_duplicates.classes(docs)
    got = sorted((r.doc_id or 0, r.class_id) for r in found.collect())
    assert got[0][1] == got[1][1] < 0 and got[2:] == [(7, 7), (7, 7)]
    assert near_duplicates.classes(docs.limit(0))[0].count() == 0
    assert near_duplicates.keep_one(docs).count() == 2


def test_components_of_a_long_path(spark):
    r = random.Random(0)
    ids = r.sample(range(1000), 40)
    links = spark.createDataFrame([*zip(ids, ids[1:]), (5000, 5001)], "a long, b long")
    got = {x.node: x.component for x in components.components(links).collect()}
    assert got == {**{i: min(ids) for i in ids}, 5000: 5000, 5001: 5000}


def test_embeddings_equal_brute_force(spark):
    r = np.random.default_rng(0)
    base = r.normal(size=(5, 8))
    rows = [(i + 10, [float(np.float32(x)) for x in base[r.integers(5)] + r.normal(size=8) * r.choice([0, 0.05, 0.3, 0.6])], int(r.integers(3))) for i in range(150)]
    rows += [(1, None, 1), (2, [0.0] * 8, 1), (3, [math.nan] * 8, 1), (4, [None] * 8, 0), (5, rows[0][1], None), (6, [], 1), (7, [1.0, 2.0], 1), (8, [2.0, 4.0], 1), (9, [math.inf] + [1.0] * 7, 2)]
    n = len(rows)
    good = [x is not None and y is not None and len(x) > 0 and all(c is not None and math.isfinite(c) for c in x) and any(x) for _, x, y in rows]
    degree, root = [0] * n, list(range(n))

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, j in itertools.combinations(range(n), 2):
        if good[i] and good[j] and rows[i][2] == rows[j][2] and len(rows[i][1]) == len(rows[j][1]):
            a, b = np.array(rows[i][1]), np.array(rows[j][1])
            if a @ b / (np.linalg.norm(a) * np.linalg.norm(b)) >= 0.93:
                degree[i] += 1
                degree[j] += 1
                root[top(i)] = top(j)
    least = {}
    for i in range(n):
        least[top(i)] = min(least.get(top(i), 10**9), rows[i][0])
    want = {rows[i][0]: (degree[i], least[top(i)], rows[i][0] == least[top(i)]) for i in range(n)}
    vectors = spark.createDataFrame([(*row, 1) for row in rows], "vec_id long, embedding array<double>, label int, links int")
    for tile in (None, 16):
        got = {x.vec_id: (x.n_links, x.component_id, x.kept) for x in embeddings.near_duplicates(vectors, tile=tile).collect()}
        assert got == want
    assert embeddings.near_duplicates(vectors.limit(0)).count() == 0


def test_embeddings_of_repeated_ids_and_dense_groups(spark, monkeypatch):
    monkeypatch.setattr(embeddings, "PRODUCTS", 50)
    monkeypatch.setattr(embeddings, "PAIRS", 7)
    base = [1.0, 2.0, 3.0, 4.0]
    rows = [(i, [x + 0.001 * ((i * k) % 5) for k, x in enumerate(base)], 1) for i in range(60)] + [(7, [-1.0, 0.0, 0.0, 0.0], 1), (61, [-1.0, 0.001, 0.0, 0.0], 1), (61, [-1.0, 0.001, 0.0, 0.0], 1)]
    vectors = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    got = collections.Counter((x.vec_id, x.n_links, x.component_id) for x in embeddings.near_duplicates(vectors).collect())
    # Id 7 has a vector in either group: two vectors, each in its own component.
    assert sum(got.values()) == 63 and got[(7, 59, 0)] == 1 and got[(7, 2, 7)] == 1 and got[(61, 2, 7)] == 2
    assert all(got[(i, 59, 0)] == 1 for i in range(60))
    one = spark.createDataFrame([(1, base, 1), (1, base[::-1], 1), (2, base, 1)], "vec_id long, embedding array<float>, label int")
    assert sorted(map(tuple, embeddings.near_duplicates(one).collect())) == [(1, 0, 1, True), (1, 1, 1, True), (2, 1, 1, False)]


def test_quantisation_bound_is_rigorous():
    r = np.random.default_rng(1)
    u = r.normal(size=(200, 64))
    u /= np.linalg.norm(u, axis=1)[:, None]
    c, s, e, m = embeddings.quantise(u)
    product = (c.astype(int) @ c.astype(int).T) * s[:, None] * s[None, :]
    bound = m[:, None] * e[None, :] + e[:, None] * m[None, :] + e[:, None] * e[None, :]
    assert (np.abs(u @ u.T - product) <= bound + 1e-12).all()


@pytest.mark.parametrize("n", [1, 2, 3, 5, 97, 1000])
def test_permutation(spark, n):
    got = [r[0] for r in spark.range(n).select(sharding.permute("id", n, 1)).collect()]
    assert sorted(got) == list(range(n))


def test_shards(spark):
    docs = spark.createDataFrame([(i if i % 50 else None, None if i % 9 == 0 else f"é{i}", 1) for i in range(403)] + [(7, "x", 1)] * 3, "doc_id long, text string, size int")
    rows = sharding.shard(docs).collect()
    per = collections.defaultdict(list)
    for r in rows:
        per[r.shard].append(r.slot)
    assert len(rows) == 406 and all(sorted(s) == list(range(len(s))) for s in per.values())
    assert max(map(len, per.values())) - min(map(len, per.values())) <= 1
    assert all(r.text_crc32 == zlib.crc32(f"é{r.doc_id}".encode()) for r in rows if r.doc_id and r.doc_id % 9 and r.size > 2 and r.doc_id != 7)
    assert sorted(map(tuple, sharding.shard(docs).collect()), key=str) == sorted(map(tuple, rows), key=str)
    assert sharding.shard(docs.limit(0)).count() == 0


def test_mix_meets_its_targets(spark):
    r = random.Random(2)
    docs = spark.createDataFrame([(i, " ".join("w" for _ in range(r.randint(0, 30))) or None, r.choice(["a", "b", "c", "d", None]), 0) for i in range(900)], "doc_id long, text string, source string, size int")
    rows = mixing.mix(docs).collect()
    source = {x.doc_id: x.source for x in docs.collect()}
    total = sum(x["size"] for x in rows)
    per = collections.defaultdict(lambda: [0, 0, 0.0])
    for x in rows:
        p = per[source[x.doc_id]]
        p[0] += x["size"]
        p[1] += x.taken
        p[2] = x.target
        assert x.taken in (0, x["size"], 2 * x["size"])
    names = sorted((s for s in per if s), key=str) + [None]
    weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(names)}
    want, full = {}, set()
    while True:  # share, stop at twice the size, share the rest again
        left = 1.5 * total - sum(2 * per[s][0] for s in full)
        share = left / sum(weight[s] for s in names if s not in full)
        want = {s: 2 * per[s][0] if s in full else share * weight[s] for s in names}
        over = {s for s in names if want[s] > 2 * per[s][0]}
        if not over:
            break
        full |= over
    for s in names:
        assert per[s][2] == pytest.approx(want[s], abs=1e-5)
        assert abs(per[s][1] - want[s]) <= 30
    assert mixing.repeat(docs).count() == sum(x.copies for x in rows)
    assert mixing.mix(docs.limit(0)).count() == 0


@pytest.mark.parametrize("lean", [0.5, 0.0, 1.0])
def test_inclusion_follows_the_odds(spark, lean):
    """One set of documents under 400 sources, each with random numbers of its own: shares taken are the probabilities."""
    sizes = [1, 1, 2, 3, 5, 8, 13, 20, 20, 33, 40, 57, 64, 90, 130, 7, 9, 11, 300, 2] * 2
    copies = 400
    docs = spark.createDataFrame([(s * 1000 + i, "w " * k, f"s{s}") for s in range(copies) for i, k in enumerate(sizes)], "doc_id long, text string, source string")
    rows = mixing.mix(docs, weights=(1.0,), volume=0.6, lean=lean).collect()
    taken, p = collections.Counter(), {}
    for x in rows:
        taken[x["size"]] += x.copies / copies / sizes.count(x["size"])
        p[x["size"]] = x.inclusion
        assert x.copies in (0, 1) and x.inclusion == pytest.approx(x.inclusion)
    assert sum(p[k] * k for k in sizes) == pytest.approx(0.6 * sum(sizes))
    odds = {k: p[k] / (1 - p[k]) / 2 ** (lean * (k.bit_length() - 1)) for k in sizes}
    assert max(odds.values()) == pytest.approx(min(odds.values()))
    assert all(abs(taken[k] - p[k]) < 0.09 for k in sizes)
    by_source = collections.Counter()
    for x in rows:
        by_source[x.doc_id // 1000] += x.taken
    assert all(abs(t - 0.6 * sum(sizes)) <= 150 for t in by_source.values())


def test_mix_of_repeated_rows_and_null_ids(spark):
    docs = spark.createDataFrame([(None, "a b c", "s", 1)] * 3 + [(1, "a", "s", 1), (1, "a b", "s", 1), (1, "a", "s", 1), (2, None, None, 1), (3, "x " * 50_000, None, 1)], "doc_id long, text string, source string, rank int")
    rows = mixing.mix(docs).collect()
    assert len(rows) == 8 and all(x.taken == x["size"] * x.copies and x.copies <= 2 for x in rows)
    assert len({(x.doc_id, x["size"], x.copies) for x in rows}) == len({(x.doc_id, x["size"]) for x in rows})
    again = mixing.mix(docs.repartition(5)).collect()
    assert sorted(map(str, rows)) == sorted(map(str, again))
    assert mixing.repeat(docs).columns == docs.columns


def test_pipeline_stages(spark, tmp_path):
    pipeline = pytest.importorskip("corpus_pipeline")
    r = random.Random(4)
    syllables = "the and ing tion er ha on at en st ou le".split()
    word = lambda: "".join(r.choice(syllables) for _ in range(r.randint(1, 4)))
    good = lambda: ". ".join(" ".join(word() for _ in range(9)) for _ in range(r.randint(3, 8)))
    bad = lambda: "!! ".join(word().upper() for _ in range(70))
    t = [good() if i % 4 else bad() for i in range(300)]
    t[21], t[23] = t[22], t[22].replace("the", "the", 1) + " mail a.b@example.com end"
    spark.createDataFrame([(i, x, "en", f"s{i % 3}", len(x)) for i, x in enumerate(t)], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, int(i % 4 > 0), 0) for i in range(300)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    kept = {}
    for name, stage in pipeline.STAGES:
        out = stage(spark, docs, str(tmp_path))
        if name != pipeline.STAGES[-1][0]:
            assert out.columns == docs.columns
        out.write.parquet(f"{tmp_path}/{name}")
        kept[name] = docs = spark.read.parquet(f"{tmp_path}/{name}")
    ids = {n: [x.doc_id for x in f.select("doc_id").collect()] for n, f in kept.items()}
    assert sum(i % 4 > 0 for i in ids["quality"]) >= 220 and sum(i % 4 == 0 for i in ids["quality"]) <= 4
    assert 21 in ids["near_duplicates"] and 22 not in ids["near_duplicates"] and len(set(ids["near_duplicates"])) == len(ids["near_duplicates"])
    assert sorted(ids["pii"]) == sorted(ids["near_duplicates"]) and kept["pii"].where(F.col("text").contains("@example")).count() == 0
    assert set(ids["mixing"]) <= set(ids["pii"]) and sorted(ids["bpe"]) == sorted(ids["mixing"])
    got = {(x.doc_id, x.decoded_sha256) for x in kept["bpe"].collect()}
    assert got == {(x.doc_id, hashlib.sha256(x.text.encode()).hexdigest()) for x in kept["mixing"].collect()}


def test_near_duplicates_of_an_id_with_two_texts(spark):
    """Id 5 holds two texts, and 8 is near to the second: it joins in whatever order the rows come."""
    r = random.Random(9)
    words = ["".join(r.choice("abcdefgh") for _ in range(5)) for _ in range(200)]
    one, two = " ".join(words[:40]), " ".join(words[100:140])
    rows = [(5, one, "m", "n"), (5, two, "m", "n"), (8, two + " more", "m", "n"), (9, " ".join(words[50:90]), "m", "n")]
    for order in (rows, rows[::-1]):
        docs = spark.createDataFrame(list(order), "doc_id long, text string, _mark string, _node string").coalesce(1)
        found, _ = near_duplicates.classes(docs)
        assert sorted((x.doc_id, x.class_id) for x in found.collect()) == [(5, 5), (5, 5), (8, 5), (9, 9)]
        if order is rows:
            kept = near_duplicates.keep_one(docs)
            assert kept.columns == docs.columns and sorted(x.doc_id for x in kept.collect()) == [5, 9]
            assert {x._mark for x in kept.collect()} == {"m"}
    docs = spark.createDataFrame([(None, two), (8, two + " more"), (3, two + " more more")], "doc_id long, text string")
    assert {x.class_id for x in near_duplicates.classes(docs)[0].collect()} == {3}


@pytest.mark.parametrize("tile", [3, 2048])
def test_near_duplicates_verify_every_pair_where_least_is_zero(spark, monkeypatch, tile):
    monkeypatch.setattr(near_duplicates, "TILE", tile)
    monkeypatch.setattr(near_duplicates, "TILE_BYTES", 2000 if tile == 3 else 8_000_000)
    t = corpus(6)
    docs = spark.createDataFrame(list(enumerate(t)), "doc_id long, text string").repartition(3)
    found, _ = near_duplicates.classes(docs, least=0.0)
    assert {x.doc_id: x.class_id for x in found.collect()} == dict(enumerate(brute(t)))


def test_near_duplicates_of_long_texts(spark):
    r = random.Random(3)
    words = [f"w{r.randint(0, 10**6)}" for _ in range(60_000)]
    docs = spark.createDataFrame([(1, " ".join(words)), (2, " ".join(words[:-200])), (3, " ".join(words[30_000:])), (4, "")], "doc_id long, text string")
    assert sorted((x.doc_id, x.class_id) for x in near_duplicates.classes(docs)[0].collect()) == [(1, 1), (2, 1), (3, 3), (4, 4)]
