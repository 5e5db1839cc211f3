"""Vectors as tables (id, x): sums over joins by id; several products share one pass."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def dot(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: value."""
    return a.join(b.withColumnRenamed("x", "y"), "id").agg(F.coalesce(F.sum(F.col("x") * F.col("y")), F.lit(0.0)).alias("value"))


def norm2(a: DataFrame) -> DataFrame:
    return a.agg(F.sqrt(F.coalesce(F.sum(F.col("x") * F.col("x")), F.lit(0.0))).alias("value"))


def axpy(alpha: float, a: DataFrame, b: DataFrame) -> DataFrame:
    """alpha * a + b."""
    return _pair(a, b, lambda x, y: alpha * x + y)


def add(a: DataFrame, b: DataFrame) -> DataFrame:
    return axpy(1.0, a, b)


def sub(a: DataFrame, b: DataFrame) -> DataFrame:
    return _pair(a, b, lambda x, y: x - y)


def hadamard(a: DataFrame, b: DataFrame) -> DataFrame:
    return _pair(a, b, lambda x, y: x * y)


def scale(alpha: float, a: DataFrame) -> DataFrame:
    return a.select("id", (alpha * F.col("x")).alias("x"))


def fill(spark, n: int, value: float) -> DataFrame:
    return spark.range(n).select("id", F.lit(float(value)).alias("x"))


def random_unit(spark, n: int, seed: int) -> DataFrame:
    """A unit vector whose entries come from a hash of seed and id, so the same on every cluster."""
    raw = spark.range(n).select("id", (F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("id").cast("string"))), 1, 8), 16, 10).cast("double") / 2**31 - 1).alias("x"))
    length = norm2(raw).first()[0]
    return scale(1 / length, raw) if length else raw


def project(a: DataFrame, unit: DataFrame) -> DataFrame:
    """a without its part along a unit vector."""
    return axpy(-dot(a, unit).first()[0], unit, a)


def gram(vectors: list[DataFrame]) -> DataFrame:
    """i, j, value for i <= j: all products in one pass over the joined vectors."""
    wide = vectors[0].withColumnRenamed("x", "x0")
    for k, v in enumerate(vectors[1:], 1):
        wide = wide.join(v.withColumnRenamed("x", f"x{k}"), "id")
    pairs = [(i, j) for i in range(len(vectors)) for j in range(i, len(vectors))]
    sums = wide.agg(*(F.sum(F.col(f"x{i}") * F.col(f"x{j}")).alias(f"g{i}_{j}") for i, j in pairs))
    return sums.select(F.explode(F.array(*(F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.col(f"g{i}_{j}").alias("value")) for i, j in pairs))).alias("g")).select("g.*")


def _pair(a: DataFrame, b: DataFrame, f) -> DataFrame:
    return a.join(b.withColumnRenamed("x", "y"), "id").select("id", f(F.col("x"), F.col("y")).alias("x"))
