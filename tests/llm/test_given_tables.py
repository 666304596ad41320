"""The registered queries on the smallest given tables, each against a second computation."""

import hashlib
import os
import zlib

import pytest

public_tokenizers = pytest.importorskip("public_tokenizers")
from aggclust.llm import fingerprints, quality, registry, sharding  # noqa: E402
from tests.llm.test_corpus_operators import brute  # noqa: E402
from tests.llm.test_text_operators import BASE  # noqa: E402

SF = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="the given tables are not here")


@pytest.fixture(scope="module")
def rows(spark):
    return sorted(((r.doc_id, r.text or "", r.source) for r in spark.read.parquet(f"{SF}/documents.parquet").collect()), key=str)


def run(spark, name):
    return registry.queries()[name](spark, SF).collect()


def test_op1_on_all_documents(spark, rows):
    got = {x.doc_id: x for x in run(spark, "op1_fingerprints")}
    order = sorted(rows, reverse=True)
    assert set(got) == {i for i, *_ in rows}
    for (i, text, _), (_, after, _) in zip(order, order[1:] + order[:1]):
        edited = fingerprints.edit(text, after)
        own, new, behind = (set(fingerprints.paragraphs([t])[1].tolist()) for t in (text, edited, after))
        like = lambda a, b: len(a & b) / len(a | b) if a | b else 1.0
        x = got[i]
        assert x.n_chars == len(text) and x.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        assert x.near_edited == pytest.approx(like(own, new)) and x.near_next == pytest.approx(like(own, behind))
        assert x.fingerprint == fingerprints.fingerprints([text], fingerprints.paragraphs([text]))[0]


def test_op3_on_all_documents(spark, rows):
    import re

    got = {x.doc_id: x for x in run(spark, "op3_pii")}
    for i, text, _ in rows:
        flat = [f"{k}:{m.start()}:{m.end()}" for k, p, ok in BASE for m in re.finditer(p, text) if ok(m[0])]
        assert got[i].base_sha256 == hashlib.sha256(",".join(flat).encode()).hexdigest() and got[i].spans.startswith(",".join(flat))


def test_op4_on_all_documents(spark, rows):
    t = [x[1] for x in rows]
    want = brute(t)
    assert {x.doc_id: x.class_id for x in run(spark, "op4_near_duplicates")} == {rows[k][0]: min(rows[j][0] for j in range(len(t)) if want[j] == want[k]) for k in range(len(t))}


def test_op6_on_all_documents(spark, rows):
    """Every place again by whole-number arithmetic: order by the mixed id, Feistel rounds, cycle walking."""
    p, n = sharding.PRIME, len(rows)

    def mixed(x):
        h = x % p
        for k in range(3):
            h = (h * h + h * sharding.MULTIPLIERS[k] % p + (sharding.OFFSETS[k] + 1 * (k + 1)) % p) % p
        return h

    a, b = sharding.grid(n)

    def once(x):
        u, v = x % a, x // a
        for k, (m, o) in enumerate(zip(sharding.MULTIPLIERS, sharding.OFFSETS)):
            h = (v % p * m + (o + 1) % p) % p
            u, v = v, (u + (h * h + h) % p) % ((a, b)[k % 2])
        return u + v * a

    def place(x):
        x = once(x)
        while x >= n:
            x = once(x)
        return x

    got = {x.doc_id: x for x in run(spark, "op6_sharding")}
    for at, (i, text, _) in enumerate(sorted(rows, key=lambda r: (mixed(r[0]), r[0]))):
        x, to = got[i], place(at)
        assert (x.shard, x.slot) == (to % 8, to // 8) and x.law == "rows" and x.grown_shard is None
        assert x.text_crc32 == zlib.crc32(text.encode())


def test_op7_and_op8_on_all_documents(spark, rows):
    import base64

    import tiktoken
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb"))}
    lib = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    counts = {x.doc_id: x for x in run(spark, "op7_token_counts")}
    codes = {x.doc_id: x for x in run(spark, "op8_bpe_codec")}
    for i, text, _ in rows:
        n = len(tok.encode(text, add_special_tokens=False).ids)
        assert (counts[i].n_tokens, counts[i].n_bytes, counts[i].over_limit) == (n, len(text.encode()), n > 1024)
        ids = lib.encode_ordinary(text)
        assert codes[i].n_tokens == len(ids) and codes[i].ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert codes[i].decoded_sha256 == hashlib.sha256(text.encode()).hexdigest()


def test_op10_on_all_documents(spark, rows):
    got = {x.doc_id: x for x in run(spark, "op10_quality")}
    label = {r.doc_id: r.quality for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    assert set(got) == {i for i, *_ in rows}
    assert all(x.held_out == (zlib.crc32(str(i).encode()) % 5 == 0) and x.predicted == int(x.score >= 0.3) and 0 <= x.score <= 1 for i, x in got.items())
    held = [(got[i].predicted, label[i]) for i in label if i in got and got[i].held_out]
    assert sum(a == b for a, b in held) >= 0.6 * len(held)


def test_quality_of_empty_tables_and_repeated_rows(spark):
    docs = spark.createDataFrame([(i, "good words here " * (1 + i % 5) if i % 2 else "BAD!! | " * (3 + i % 7), "s") for i in range(80)] * 2 + [(None, None, "s")], "doc_id long, text string, score string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(80)] * 2, "doc_id long, quality int")
    got = quality.quality_scores(docs, quality.learn(docs, labels)).collect()
    assert len(got) == 161 and len({(x.doc_id, x.score) for x in got}) == 81
    assert quality.quality_scores(docs.limit(0), quality.learn(docs, labels)).count() == 0
    assert quality.learn(docs.limit(0), labels).constant == 1.0


def test_quality_learns_from_whole_texts(spark):
    """Good and bad differ only behind 40,000 common bytes: labels of whole texts tell them apart, a prefix would not."""
    import random

    r = random.Random(5)
    common = " ".join(f"w{r.randint(0, 99)}" for _ in range(9000))
    tail = {1: ["lovely clear prose about rivers and their boats", "calm reading for a long evening by the sea"], 0: ["BUY NOW!!! CLICK | CLICK | WIN $$$", "FREE!!! ### DEAL ### CLICK HERE NOW"]}
    docs = spark.createDataFrame([(i, common[: 40_000 + 7 * i] + " ".join(r.choice(tail[i % 2]) for _ in range(1500))) for i in range(60)], "doc_id long, text string")
    model = quality.learn(docs, spark.createDataFrame([(i, i % 2) for i in range(60)], "doc_id long, quality int"))
    got = [(x.predicted, x.doc_id % 2) for x in quality.quality_scores(docs, model, 0.5).collect()]
    assert sum(a == b for a, b in got) >= 57


def test_long_texts_and_repeated_rows(spark):
    from aggclust.llm import pii

    long = "plain words 10.0.0.7 and a.b@example.com, " * 8000
    docs = spark.createDataFrame([(1, long, "s"), (1, long, "s"), (2, "", "s"), (3, long[1:], None)], "doc_id long, text string, size string")
    prints = sorted((x.doc_id, x.n_chars, x.near_next) for x in fingerprints.with_next(docs).collect())
    assert [p[:2] for p in prints] == [(1, len(long)), (1, len(long)), (2, 0), (3, len(long) - 1)]
    assert sorted(x.size for x in sharding.shard(docs).collect()) == [1, len(long), len(long) + 1, len(long) + 1]
    spans = [(x.doc_id, x.n_email, x.n_ip, x.spans) for x in pii.pii(docs).collect()]
    assert sorted(s[:3] for s in spans) == [(1, 8000, 8000), (1, 8000, 8000), (2, 0, 0), (3, 8000, 8000)] and len(set(spans)) == 3


def test_pipeline_of_odd_rows(spark, tmp_path):
    """Null and empty texts, null sources, repeated rows, a clashing column; and no rows at all."""
    pipeline = pytest.importorskip("corpus_pipeline")
    odd = [(1, None, None, None, 0, "m"), (2, "", "en", "s", 0, "m"), (3, "plain words of no interest here", "en", None, 31, "m"), (3, "plain words of no interest here", "en", None, 31, "m"), (None, "x", None, "s", 1, None)]
    schema = "doc_id long, text string, lang string, source string, n_chars long, _mark string"
    for name, part in (("odd", odd), ("none", [])):
        folder = f"{tmp_path}/{name}"
        spark.createDataFrame(part, schema).write.parquet(f"{folder}/documents.parquet")
        spark.createDataFrame([(3, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
        got = pipeline.run(spark, folder)
        assert got.columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
        assert {x.doc_id for x in got.collect()} <= {1, 2, 3, None} and (part or got.count() == 0)
