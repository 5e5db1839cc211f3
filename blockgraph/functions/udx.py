"""User-defined functions, aggregates, table functions and a generator source; none is on a path that built-ins can express."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import DoubleType, IntegerType, LongType, StructField, StructType


@F.pandas_udf(DoubleType())
def half_life(x: pd.Series) -> pd.Series:
    """x / 2, vectorised."""
    return x / 2


@F.arrow_udf(LongType())
def block_code(p: pa.Array, q: pa.Array) -> pa.Array:
    """p * 1000 + q over Arrow arrays."""
    import pyarrow.compute as pc

    return pc.add(pc.multiply(p.cast(pa.int64()), 1000), q.cast(pa.int64()))


@F.pandas_udf(DoubleType())
def fold_sum(x: pd.Series) -> float:
    """A sum as a grouped aggregate: the form a ``combine`` takes that Spark has no function for."""
    return float(x.sum())


@F.udtf(returnType=StructType([StructField(c, IntegerType()) for c in ("step", "q", "p")]))
class Zigzag:
    """The order of blocks of a beta x beta grid."""

    def eval(self, beta: int):
        for step in range(beta * beta):
            q, k = divmod(step, beta)
            yield step + 1, q, k if q % 2 == 0 else beta - 1 - k


def rmat_rows(scale: int, seed: int, begin: int, end: int) -> Iterator[tuple[int, int]]:
    """Edges begin .. end - 1 of the recursive-matrix graph of ``sources.graphs.rmat``."""
    a, b, c = (round(x * 65536) for x in (0.57, 0.76, 0.95))
    for i in range(begin, end):
        src = dst = 0
        for level in range(scale):
            d = int(hashlib.md5(f"{seed}:{i}:{level}".encode()).hexdigest()[:4], 16)
            src, dst = src * 2 + (d >= b), dst * 2 + (a <= d < b or d >= c)
        yield src, dst


@F.udtf(returnType=StructType([StructField(c, LongType()) for c in ("src", "dst")]))
class RmatEdges:
    """Edges of one range of numbers."""

    def eval(self, scale: int, seed: int, begin: int, end: int):
        yield from rmat_rows(scale, seed, begin, end)


class RmatSource(DataSource):
    """spark.read.format("rmat"): options scale, k, seed, parts; edges: so many in place of k * 2 ** scale. Each edge with its number."""

    @classmethod
    def name(cls) -> str:
        return "rmat"

    def schema(self) -> str:
        return "id long, src long, dst long"

    def reader(self, schema) -> DataSourceReader:
        return RmatReader(self.options)


class RmatReader(DataSourceReader):
    def __init__(self, options):
        self.scale, self.k, self.seed, self.parts = (int(options.get(n, d)) for n, d in (("scale", 8), ("k", 3), ("seed", 7), ("parts", 4)))
        self.edges = int(options["edges"]) if "edges" in options else None

    def partitions(self):
        total = self.k * 2**self.scale if self.edges is None else self.edges
        cuts = np.linspace(0, total, self.parts + 1).astype(int).tolist()
        return [InputPartition(c) for c in zip(cuts[:-1], cuts[1:], strict=True)]

    def read(self, partition):
        begin, end = partition.value
        for i, (src, dst) in enumerate(rmat_rows(self.scale, self.seed, begin, end), begin):
            yield i, src, dst


def _block_fold(edges: pa.Table, values: pa.Table) -> pa.Table:
    ids, x = values["id"].to_numpy(), values["x"].to_numpy()
    order = np.argsort(ids)
    at = np.searchsorted(ids[order], edges["src"].to_numpy())
    dst, back = np.unique(edges["dst"].to_numpy(), return_inverse=True)
    sums = np.bincount(back, weights=x[order][at], minlength=len(dst))
    return pa.table({"dst": dst, "acc": sums})


def kernel_fold(edges: DataFrame, slices: DataFrame) -> DataFrame:
    """dst, acc: the fold of the dense path, one destination interval at a time as arrays (edges: q, src, dst; slices: q, src, x).

    An interval's slices and edges are in memory together, which is what the number of intervals is chosen for."""
    slices = slices.select(F.col("q").alias("slice_q"), F.col("src").alias("id"), "x")
    return edges.groupBy("q").cogroup(slices.groupBy("slice_q")).applyInArrow(_block_fold, "dst long, acc double")
