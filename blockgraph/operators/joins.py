"""Joins that Spark has no operator for, as equi-joins and windows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def range_join(points: DataFrame, ranges: DataFrame, point: str, lo: str, hi: str, width: int) -> DataFrame:
    """points with the ranges lo..hi (both ends in) that hold them: an equi-join on cells of ``width``; a range is in each cell it touches."""
    cell = lambda c: F.expr(f"{c} div {width}")
    spread = ranges.withColumn("_cell", F.explode(F.sequence(cell(lo), cell(hi))))
    return points.withColumn("_cell", cell(point)).join(spread, "_cell").where(F.col(point).between(F.col(lo), F.col(hi))).drop("_cell")


def asof_join(left: DataFrame, right: DataFrame, by: str, at: str, tie: str, value: str) -> DataFrame:
    """left with the ``value`` of the latest row of right before it (by ``at``, then id: a row of right ties below one of left by id).

    One shuffle: both sides in one window per key, no pairs."""
    both = left.select(by, at, F.col(tie).alias("_id"), F.lit(1).alias("_left"), F.lit(None).cast(right.schema[value].dataType).alias(value))
    both = both.unionByName(right.select(by, at, F.col(value).alias("_id"), F.lit(0).alias("_left"), value))
    w = Window.partitionBy(by).orderBy(at, "_id").rowsBetween(Window.unboundedPreceding, -1)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(w)).where("_left = 1").select(by, at, F.col("_id").alias(tie), value)


def interval_join(left: DataFrame, right: DataFrame, by: str, left_at: str, right_at: str, seconds: int) -> DataFrame:
    """Pairs of a key with right_at within 0 .. seconds after left_at: equi-join on key and time cell, a left row in two cells."""
    cell = lambda c: F.expr(f"unix_micros({c}) div {seconds * 1_000_000}")
    a = left.withColumn("_cell", F.explode(F.array(cell(left_at), cell(left_at) + 1)))
    b = right.withColumn("_cell", cell(right_at))
    gap = F.expr(f"unix_micros({right_at}) - unix_micros({left_at})")
    return a.join(b, [by, "_cell"]).where((gap >= 0) & (gap <= seconds * 1_000_000)).drop("_cell")


def salted_join(facts: DataFrame, side: DataFrame, key: str, salts: int) -> DataFrame:
    """Equi-join with a hot key spread over ``salts`` tasks; the other side is repeated as often."""
    left = facts.withColumn("_salt", F.pmod(F.xxhash64(*facts.columns), F.lit(salts)).cast("int"))
    right = side.withColumn("_salt", F.explode(F.array(*(F.lit(i) for i in range(salts)))))
    return left.join(right, [key, "_salt"]).drop("_salt")
