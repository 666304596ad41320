"""Where results go, and how lineage is cut."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def checkpoint_folder(spark: SparkSession) -> str:
    """The shared folder the cluster names; one of our own only where none is set and all runs on one machine, as in tests."""
    found = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if found is None:
        import tempfile

        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="checkpoint-"))
        found = spark.sparkContext.getCheckpointDir()
    return found


def cut_lineage(df: DataFrame) -> DataFrame:
    """Write ``df`` to the shared folder and go on from there; survives lost executors."""
    checkpoint_folder(df.sparkSession)
    return df.checkpoint()


def save(df: DataFrame, path: str, fmt: str = "parquet", by: list[str] | None = None, mode: str = "overwrite") -> None:
    writer = df.write.mode(mode).format(fmt)
    (writer.partitionBy(*by) if by else writer).save(path)


def load(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    return spark.read.format(fmt).load(path)
