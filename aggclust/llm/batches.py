"""Helpers shared by the operators that read texts in Arrow batches."""

from __future__ import annotations

import gc
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text handled together by one vectorised step; bounds the memory of a task.
SLAB = 1_000_000


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def slabs(column: pa.Array, limit: int = SLAB) -> Iterator[tuple[int, int, list[str]]]:
    """Consecutive texts of at most ``limit`` bytes, or one longer text, as Python strings.

    Only one slab is decoded at a time, and what Arrow freed goes back to the system, so a worker
    that lives through many stages stays small.
    """
    sizes = pc.binary_length(column).to_pylist()
    begin = size = 0
    for at, n in enumerate(sizes):
        if at > begin and size + n > limit:
            yield begin, at, column.slice(begin, at - begin).to_pylist()
            begin, size = at, 0
        size += n
    if begin < len(sizes):
        yield begin, len(sizes), column.slice(begin).to_pylist()
    pa.default_memory_pool().release_unused()


def per_document(
    docs: DataFrame,
    work: Callable[[list[str]], list[list]],
    schema: str,
    id_col: str = "doc_id",
    text_col: str = "text",
) -> DataFrame:
    """Apply ``work`` (texts of a slab -> one list per output column) to every row.

    A null text is read as empty.  The id travels unchanged, null or repeated.  No shuffle: one
    pass over the scan's own splits, and a lost executor only costs its splits.
    """
    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    out = f"doc_id long, {schema}"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = None
        for batch in batches:
            ids = batch.column(0)
            for begin, end, texts in slabs(batch.column(1)):
                cols = work(texts)
                names = names or [part.strip().split(" ")[0] for part in schema.split(",")]
                yield pa.RecordBatch.from_arrays([ids.slice(begin, end - begin), *(pa.array(c) for c in cols)], names=["doc_id", *names])

    return picked.mapInArrow(run, out)


def plan_bytes(df: DataFrame) -> int:
    """Bytes of ``df`` by Spark's own estimate, for a scan the size of its files; nothing is read.  0 where Spark does not know."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return size if size < 1 << 60 else 0


def shared_folder(spark: SparkSession) -> None:
    """Use the cluster's own checkpoint folder; set one only where none is set and all runs on one machine, as in tests."""
    if spark.conf.get("spark.checkpoint.dir", None) is None and spark.sparkContext.getCheckpointDir() is None:
        import tempfile

        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="checkpoint-"))


def release(spark: SparkSession) -> None:
    """Let Spark remove the shuffle files and checkpoints that nothing refers to any more.

    Its cleaner follows the driver's garbage collection, which small driver heaps may not see for long.
    """
    gc.collect()
    spark._jvm.System.gc()


def cut(df: DataFrame) -> DataFrame:
    """Write ``df`` to the shared checkpoint folder and read it from there."""
    shared_folder(df.sparkSession)
    return df.checkpoint()
