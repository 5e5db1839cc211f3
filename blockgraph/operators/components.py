"""Connected components of an edge table by alternating large and small stars; every step is a grouped minimum and a join.

An edge table of at most ``small`` rows (counted first; ``SMALL`` unless the caller says otherwise, 0 for never) is settled by one task
that holds a forest of its vertices instead: the same labels in one step."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockgraph.storage import cut

SMALL = 500_000


def forest(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Vertices of the edges and the smallest vertex of each one's component: hooking to the smaller root, then pointer jumps."""
    ids, at = np.unique(np.concatenate([src, dst]), return_inverse=True)
    a, b = at[: len(src)], at[len(src) :]
    root = np.arange(len(ids))
    while True:
        ra, rb = root[a], root[b]
        apart = ra != rb
        if not apart.any():
            return ids, ids[root]
        a, b, ra, rb = a[apart], b[apart], ra[apart], rb[apart]
        np.minimum.at(root, np.maximum(ra, rb), np.minimum(ra, rb))
        while True:
            up = root[root]
            if (up == root).all():
                break
            root = up


def _forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    parts = [(b.column("a").to_numpy(), b.column("b").to_numpy()) for b in batches]
    a, b = (np.concatenate([p[i] for p in parts]) if parts else np.zeros(0, np.int64) for i in range(2))
    ids, roots = forest(a, b)
    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(roots)], ["node", "component"])


def _stars(edges: DataFrame, large: bool) -> DataFrame:
    """edges (a > b). Each node's neighbours (large: the greater ones, from all; small: the smaller ones) meet at its smallest one."""
    near = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))) if large else edges
    least = near.groupBy("a").agg(F.min("b").alias("low")).withColumn("low", F.least("a", "low"))
    moved = near.join(least, "a")
    if large:
        moved = moved.where("b > a").select(F.col("b").alias("a"), F.col("low").alias("b"))
    else:
        moved = moved.select(F.col("b").alias("a"), F.col("low").alias("b")).unionByName(least.select("a", F.col("low").alias("b")))
    return moved.where("a <> b").distinct()


def _is_stars(edges: DataFrame) -> bool:
    """Whether every node has one edge to a smaller node, or only edges to greater ones."""
    ends = edges.select(F.col("a").alias("x"), F.lit(1).alias("leaf"), F.lit(0).alias("middle")).unionByName(edges.select(F.col("b").alias("x"), F.lit(0).alias("leaf"), F.lit(1).alias("middle")))
    return not ends.groupBy("x").agg(F.sum("leaf").alias("leaf"), F.max("middle").alias("middle")).where("leaf + middle > 1").limit(1).count()


def components(edges: DataFrame, a: str = "a", b: str = "b", small: int | None = None) -> DataFrame:
    """node, component (its smallest node) for every node with an edge to another one.

    Null ends are no edges; an empty table gives an empty one."""
    small = SMALL if small is None else small
    now = cut(edges.select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b")).where("a > b").distinct(), "stars")
    if small and now.limit(small + 1).count() <= small:
        return cut(now.coalesce(1).mapInArrow(_forest, "node long, component long"), "components")
    while not _is_stars(now):
        now = cut(_stars(_stars(now, True), False), "stars")
    leaves = now.select(F.col("a").alias("node"), F.col("b").alias("component"))
    return leaves.unionByName(leaves.select(F.col("component").alias("node"), "component").distinct())
