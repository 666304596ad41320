"""Quality by compression: zstandard dictionaries of good and of bad text.

Each text is cut into blocks, every block is compressed with the good dictionary, with the bad
one and with none, and the differences of the compressed sizes, divided by the text's bytes, go
through a logistic calibration.  Labels are learned from a bounded sample of rows, in whole texts:
per class the ``per_class`` labelled documents of lowest hashed id, half of them for the
dictionary, the others for the calibration.  Dictionaries and size differences are made in the
executors; the driver gets two dictionaries and three numbers per row of the sample.

Defined cases: a null text is empty and gets the calibration's value for no bytes; labels that
are null, repeated or without a document are ignored or used once each; of several texts of one
id the smallest is learned from; where one class has no labelled document, every score is 1.0 (no
bad ones) or 0.0 (no good ones), and 1.0 without any label.  An id that is null counts as the
empty string when rows are held out.  Repeated rows each give a row, an empty table gives none.
Other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from aggclust.llm.batches import cut, documents, slabs

PER_CLASS, DICTIONARY, BLOCK, LEVEL, THRESHOLD = 3000, 112_640, 4096, 3, 0.3


@dataclass(frozen=True)
class Model:
    good: bytes
    bad: bytes
    centre: tuple
    scale: tuple
    weights: tuple
    constant: float | None = None


def _blocks(raw: bytes) -> list[bytes]:
    return [raw[i : i + BLOCK] for i in range(0, len(raw), BLOCK)] or [b""]


@lru_cache(maxsize=4)
def _compressors(good: bytes, bad: bytes) -> list:
    plain = {"level": LEVEL, "write_content_size": False, "write_dict_id": False}
    return [zstandard.ZstdCompressor(**plain, **({"dict_data": zstandard.ZstdCompressionDict(d)} if d else {})) for d in (good, bad, b"")]


def differences(raws: list[bytes], good: bytes, bad: bytes) -> np.ndarray:
    """Per text: good minus bad, plain minus good, and plain, each per byte."""
    sizes = [[sum(len(c.compress(b)) for b in _blocks(raw)) for c in _compressors(good, bad)] for raw in raws]
    s = np.array(sizes, float).reshape(-1, 3)
    n = np.array([len(r) + 1 for r in raws], float)
    return np.stack([(s[:, 0] - s[:, 1]) / n, (s[:, 2] - s[:, 0]) / n, s[:, 2] / n], 1)


def _design(x: np.ndarray, centre, scale) -> np.ndarray:
    z = np.clip((x - np.array(centre)) / np.array(scale), -8, 8)
    return np.concatenate([np.ones((len(z), 1)), z, z * z], 1)


def _calibrate(x: np.ndarray, y: np.ndarray) -> tuple[tuple, tuple, tuple]:
    centre, scale = x.mean(0), x.std(0) + 1e-9
    p = _design(x, centre, scale)
    w = np.zeros(p.shape[1])
    ridge = 1e-2 * len(y) / 100

    def loss(v: np.ndarray) -> float:
        z = p @ v
        return float(np.sum(np.logaddexp(0, z) - y * z) + ridge * v @ v / 2)

    for _ in range(60):
        q = 1 / (1 + np.exp(-np.clip(p @ w, -40, 40)))
        step = np.linalg.solve((p * (q * (1 - q))[:, None]).T @ p + ridge * np.eye(len(w)), p.T @ (y - q) - ridge * w)
        t = 1.0
        while t > 1e-4 and loss(w + t * step) > loss(w):
            t /= 2
        w = w + t * step
        if np.abs(t * step).max() < 1e-8:
            break
    return tuple(centre), tuple(scale), tuple(w)


def _trained(size: int):
    """class and dictionary from the rows (_q, _o, _t) of one class."""

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("_o")
        blocks = [b for t in table["_t"].to_pylist() for b in _blocks(t.encode("utf-8"))]
        try:
            made = zstandard.train_dictionary(size, blocks).as_bytes()
        except zstandard.ZstdError:  # too few samples for the trainer: their bytes serve as they are
            made = b"".join(blocks)[:size] or b" "
        return pa.table({"_q": pa.array([table["_q"][0].as_py()], pa.int32()), "dictionary": pa.array([made], pa.binary())})

    return run


def _measured(good: bytes, bad: bytes):
    """_o, _q and the size differences of rows (_o, _q, _t)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, texts in slabs(batch.column(2)):
                x = differences([t.encode("utf-8") for t in texts], good, bad)
                yield pa.RecordBatch.from_arrays([*(batch.column(c).slice(lo, hi - lo) for c in (0, 1)), *(pa.array(x[:, i]) for i in range(3))], names=["_o", "_q", "a", "b", "c"])

    return run


def score_texts(model: Model, texts: list[str | None]) -> np.ndarray:
    if model.constant is not None:
        return np.full(len(texts), model.constant)
    x = differences([(t or "").encode("utf-8") for t in texts], model.good, model.bad)
    return 1 / (1 + np.exp(-np.clip(_design(x, model.centre, model.scale) @ np.array(model.weights), -40, 40)))


def scorer(model: Model):
    """A function of a text column that gives its score."""

    @F.arrow_udf("double")
    def score(texts: pa.Array) -> pa.Array:
        parts = [score_texts(model, part) for _, _, part in slabs(texts)]
        return pa.array(np.concatenate(parts) if parts else np.zeros(0), pa.float64())

    return score


def held_out(id_col: str | Column) -> Column:
    id_col = F.col(id_col) if isinstance(id_col, str) else id_col
    return F.crc32(F.coalesce(id_col.cast("string"), F.lit(""))) % 5 == 0


def learn(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS, dictionary: int = DICTIONARY) -> Model:
    """Fit on whole texts of at most ``per_class`` labelled documents of each class that are not held out."""
    rows = labels.select(F.col("doc_id").cast("long").alias("_id"), F.col("quality").cast("int").alias("_q")).where(F.col("_id").isNotNull() & ~held_out("_id"))
    known = docs.select(F.col("doc_id").cast("long").alias("_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("_t"))
    picked = None
    for k in (0, 1):
        part = rows.where(F.col("_q") == k).distinct().orderBy(F.xxhash64("_id"), "_id").limit(per_class)
        picked = part if picked is None else picked.unionByName(part)
    sample = known.join(F.broadcast(picked), "_id").groupBy("_id", "_q").agg(F.min("_t").alias("_t"))
    # The sample's rows are bounded, so a class may be put in order in one task.
    sample = cut(sample.withColumn("_o", F.row_number().over(Window.partitionBy("_q").orderBy(F.xxhash64("_id"), "_id"))))
    n = {r["_q"]: r["count"] for r in sample.groupBy("_q").count().collect()}
    if len(n) < 2:
        return Model(b"", b"", (), (), (), 0.0 if 0 in n else 1.0)
    made = sample.where("_o % 2 = 1").select("_q", "_o", "_t").groupBy("_q").applyInArrow(_trained(dictionary), "_q int, dictionary binary")
    found = {r["_q"]: bytes(r["dictionary"]) for r in made.collect()}
    rest = sample.where("_o % 2 = 0") if min(n.values()) > 1 else sample
    got = sorted(map(tuple, rest.select("_o", "_q", "_t").mapInArrow(_measured(found[1], found[0]), "_o int, _q int, a double, b double, c double").collect()))
    return Model(found[1], found[0], *_calibrate(np.array([r[2:] for r in got]), np.array([r[1] for r in got])))


def quality_scores(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    scored = docs.select(F.col("doc_id").cast("long").alias("doc_id"), scorer(model)(F.coalesce(F.col("text"), F.lit(""))).alias("score"))
    return scored.select("doc_id", held_out("doc_id").alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs``, all columns, that the classifier accepts."""
    return docs.where(scorer(model)(F.coalesce(F.col("text"), F.lit(""))) >= threshold)


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return quality_scores(docs, learn(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
