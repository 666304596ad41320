"""Queries and oracles of the clustering engine."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from aggclust.queries import basics, experiments, surround, trees

_MODULES = (basics, trees, surround, experiments)


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    return experiments.flagship(spark, sf_dir)


def queries() -> dict:
    return {name: f for m in _MODULES for name, f in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: s for m in _MODULES for name, s in m.SQL.items()}
