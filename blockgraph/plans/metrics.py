"""Accuracy and plan measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockgraph.operators import vectorops as vo
from blockgraph.plans import costmodel as cm
from blockgraph.plans import layout as lay
from blockgraph.sources.graphs import Graph


def max_abs_diff(a: DataFrame, b: DataFrame, column: str) -> float:
    """Largest difference of a column by id; infinite if the ids differ."""
    both = a.select("id", F.col(column).alias("x")).join(b.select("id", F.col(column).alias("y")), "id", "full")
    worst, lost = both.agg(F.max(F.abs(F.col("x") - F.col("y"))), F.sum(F.when(F.col("x").isNull() | F.col("y").isNull(), 1).otherwise(0))).first()
    return float("inf") if lost else float(worst or 0.0)


def same_partition(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: ids whose labels differ (labels are smallest members, so equal partitions have equal labels)."""
    both = a.select("id", F.col("label").alias("x")).join(b.select("id", F.col("label").alias("y")), "id", "full")
    return both.agg(F.coalesce(F.sum(F.when(F.col("x").eqNullSafe(F.col("y")), 0).otherwise(1)), F.lit(0)).alias("mismatches"))


def residual(apply, x: DataFrame, value: float) -> float:
    """Length of A x - value x over the length of value x."""
    return vo.norm2(vo.axpy(-value, x, apply(x))).first()[0] / abs(value * vo.norm2(x).first()[0])


def ortho_loss(basis: list[DataFrame]) -> float:
    """Largest entry of Q^T Q - I."""
    return max(abs(r.value - (r.i == r.j)) for r in vo.gram(basis).collect())  # a few vectors' products


def scans(df: DataFrame, names: tuple[str, ...] = ("",)) -> int:
    """File scans of a plan, of folders whose names start with one of ``names``."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return sum(any(f"/{n}" in line if n else True for n in names) for line in text.splitlines() if "FileScan" in line)


def exchanges(df: DataFrame) -> int:
    """Hash exchanges of a plan as planned first."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return text.count("Exchange hashpartitioning")


def exchange_rows(g: Graph, beta: int) -> DataFrame:
    """Rows that one iteration sends: combined messages, whole slices, slices of sources that occur, the printed rule, the smaller side."""
    width = lay.width_of(g.n, beta)
    b = cm.classify(lay.block_stats(lay.blocked(g.edges, g.n, beta), distinct=True), beta, width)
    return b.agg(
        F.sum("d").alias("stream"), (F.count(F.lit(1)) * width).alias("dense"), F.sum("s").alias("filtered"),
        F.sum(F.when(F.col("mode") == "dense", F.lit(width)).otherwise(F.col("d"))).alias("printed_rule"), F.sum(F.least("s", "d")).alias("smaller_side"),
    ).select(F.lit(beta).alias("beta"), "stream", "dense", "filtered", "printed_rule", "smaller_side")
