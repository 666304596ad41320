"""A training corpus in five stages, each a DataFrame in and a DataFrame out.

Every stage works on all that its predecessor kept, and all but the last return the columns of
``documents``.  ``run`` writes each stage's rows as Parquet into the cluster's shared checkpoint
folder and reads them back, so a lost executor costs at most one stage's work; a stage's folder
goes once the next stage is written, and the last one stays with the result.

Defined cases: a null text is scored, compared and encoded as an empty one and stays null until
then; a null source is a source of its own; repeated rows and copies leave one row; a null id is
known by its text; other columns, whatever their names, pass through all stages but the last; where
one class has no labels, all documents pass or none; empty tables give no rows.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aggclust.llm import bpe_codec, mixing, near_duplicates, pii, quality
from aggclust.llm.batches import shared_folder


def good_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the compression classifier accepts."""
    return quality.keep_good(docs, quality.learn(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of smallest id of each near-duplicate group."""
    return near_duplicates.keep_one(docs)


def without_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Confirmed spans replaced by their kind; n_chars follows the new text."""
    return pii.mask(docs).withColumn("n_chars", F.length("text").cast("long"))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix of sources takes them."""
    return mixing.repeat(docs)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token count and digests of every document's ids and of the bytes they decode to."""
    import public_tokenizers

    return bpe_codec.round_trip(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"))


STAGES = [
    ("quality", good_documents),
    ("near_duplicates", one_of_each_group),
    ("pii", without_personal_data),
    ("mixing", mixed),
    ("bpe", encoded),
]

#: Compression and ProbMinHash have no SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def _remove(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    shared_folder(spark)
    folder = f"{spark.sparkContext.getCheckpointDir()}/pipeline-{uuid.uuid4().hex}"
    docs, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        if before is not None:
            _remove(spark, f"{folder}/{before}")
        before = name
    return docs
