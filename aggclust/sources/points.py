"""Points for clustering: from columns, from files, and the feature views of the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

PRIME = 2147483647
# Weights of the row hash and its later steps.
ROW_WEIGHTS = (7919, 104729, 15485863, 1299709, 32452843, 131)
STEP, TURN = 611953999, 7919


def read(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """Parquet, ORC, CSV or JSON; text formats want a schema, as inferring one reads the input twice."""
    if fmt not in ("parquet", "orc", "csv", "json"):
        raise ValueError(f"unknown format {fmt}")
    reader = spark.read.options(**options)
    if schema:
        reader = reader.schema(schema)
    elif fmt in ("csv", "json"):
        raise ValueError(f"{fmt} needs a schema")
    return reader.format(fmt).load(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vectors(df: DataFrame, cols: list[str], id_col: str | None = None, weight: str | None = None, on_invalid: str = "error") -> DataFrame:
    """id, vec, w from numeric columns; rows with null, NaN or infinite coordinates are dropped or raise."""
    d = [F.col(c).cast("double") for c in cols]
    bad = F.lit(False)
    for c in d:
        bad = bad | c.isNull() | F.isnan(c) | (F.abs(c) == float("inf"))
    bad = F.coalesce(bad, F.lit(True))
    w = F.lit(1.0) if weight is None else F.col(weight).cast("double")
    ident = F.lit(None).cast("long") if id_col is None else F.col(id_col).cast("long")
    if on_invalid == "drop":
        df = df.where(~bad)
        vec = F.array(*d)
    elif on_invalid == "error":
        vec = F.when(bad, F.raise_error(F.lit("a coordinate is null, NaN or infinite")).cast("array<double>")).otherwise(F.array(*d))
    else:
        raise ValueError(f"unknown policy {on_invalid}")
    return df.select(ident.alias("id"), vec.alias("vec"), w.alias("w"))


def columns(points: DataFrame, d: int, prefix: str = "x", keep: tuple[str, ...] = ("id",)) -> DataFrame:
    """The vector's coordinates as columns of their own."""
    return points.select(*keep, *(F.col("vec")[i].alias(f"{prefix}{i}") for i in range(d)))


LINE5 = ("q", "p", "d", "t", "s")


def line5(df: DataFrame, keep: tuple[str, ...] = (), shift: float = 0.0) -> DataFrame:
    """Five columns of lineitem, each about [0, 50]."""
    days = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date"))
    cols = (F.col("l_quantity"), F.col("l_extendedprice") / 2085, F.col("l_discount") * 500, F.col("l_tax") * 625, days / 50)
    return df.select(*keep, *((c.cast("double") + shift).alias(n) for c, n in zip(cols, LINE5)))


def row_hash() -> Column:
    cents = F.round(F.col("l_extendedprice") * 100).cast("long")
    parts = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity")
    total = cents * ROW_WEIGHTS[5]
    for c, w in zip(parts, ROW_WEIGHTS):
        total = total + F.col(c).cast("long") * w
    return F.pmod(total, F.lit(PRIME).cast("long"))


def _uniform(b0: Column, k: int) -> Column:
    t = (b0 + k * STEP) % PRIME
    v = (t * t % PRIME + TURN * k + b0 * (2 * k + 1)) % PRIME
    return (v * v % PRIME) / F.lit(float(PRIME))


CUBE5 = ("u1", "u2", "u3", "u4", "u5")


def cube5(df: DataFrame, side: float = 100.0, keep: tuple[str, ...] = ()) -> DataFrame:
    """Five uniform coordinates from modular hashes of the row, the same in any SQL engine."""
    hashed = df.withColumn("_b", row_hash())
    return hashed.select(*keep, *((_uniform(F.col("_b"), k + 1) * side).alias(n) for k, n in enumerate(CUBE5)))


MIX5 = ("g1", "g2", "g3", "g4", "g5")


def mix5(df: DataFrame, components: int = 500, side: float = 100.0, sigma: float = 3.0, keep: tuple[str, ...] = ()) -> DataFrame:
    """Gaussian components around hashed centres: component ``l_partkey % components`` as ``comp``."""
    comp = (F.col("l_partkey") % components).cast("long")
    rows = df.withColumns({"_b": row_hash(), "comp": comp}).withColumn("_c", F.pmod(F.col("comp") * 48271 + 11, F.lit(PRIME).cast("long")) * 16807 % PRIME)
    u = [_uniform(F.col("_b"), k + 1) for k in range(6)]
    normals = []
    for i in range(0, 6, 2):
        r = F.sqrt(-2 * F.log(u[i] + 1e-9) + 1e-8)
        angle = 2 * 3.141592653589793 * u[i + 1]
        normals += [r * F.cos(angle), r * F.sin(angle)]
    return rows.select(*keep, "comp", *((_uniform(F.col("_c"), k + 1) * side + sigma * normals[k]).alias(n) for k, n in enumerate(MIX5)))


def synthetic(spark: SparkSession, gen: str, n: int, d: int = 5, seed: int = 0, clusters: int = 500, side: float = 100.0, sigma: float = 3.0, partitions: int | None = None) -> DataFrame:
    """id, vec, w of generated points, for sizes beyond the tables: ``uniform`` or ``gaussian``."""
    base = spark.range(0, n, 1, partitions) if partitions else spark.range(n)
    if gen == "uniform":
        vec = F.array(*(F.rand(seed * 1000 + i) * side for i in range(d)))
        return base.select("id", vec.alias("vec"), F.lit(1.0).alias("w"))
    if gen != "gaussian":
        raise ValueError(f"unknown generator {gen}")
    comp = F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(clusters))
    centre = [F.pmod(F.xxhash64(comp, F.lit(seed), F.lit(i)), F.lit(1_000_003)) / 1_000_003.0 * side for i in range(d)]
    return base.select("id", F.array(*(c + F.randn(seed * 1000 + i) * sigma for i, c in enumerate(centre))).alias("vec"), F.lit(1.0).alias("w"))
