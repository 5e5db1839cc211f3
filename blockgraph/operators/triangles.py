"""Triangles of an undirected graph in bounded memory and without an exchange of pairs of neighbours.

Vertices have colours. The edges are written once, packed, in a folder for each pair of colours. A task takes the folders between two or
three colours (or of one), as many edges as ``PER_TASK`` on average, and counts their triangles; so disk grows with the edges only."""

from __future__ import annotations

import math
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from functools import reduce
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blockgraph.sources.graphs import Graph
from blockgraph.storage import drop_path, own_path, settings

#: Edges of a task; edges packed at a time; pairs of neighbours looked up at a time; tasks of a job.
PER_TASK, PACKED, LOOKED_UP, TASKS = 4_000_000, 1_000_000, 1 << 17, 48


def pack(a: np.ndarray, b: np.ndarray) -> bytes:
    """Edges in the order of a, then b: steps of a, and b, each as planes of bytes, which codecs shorten."""
    return b"".join(np.ascontiguousarray(x.astype(np.int64).view(np.uint8).reshape(-1, 8).T).tobytes() for x in (np.diff(a, prepend=0), b))


def unpack(packed: bytes) -> tuple[np.ndarray, np.ndarray]:
    steps, b = (np.ascontiguousarray(x.T).view(np.int64).ravel() for x in np.frombuffer(packed, np.uint8).reshape(2, 8, -1))
    return np.cumsum(steps), b


def _chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each pair of colours of every PACKED edges."""
    held, rows = [], 0

    def flush() -> pa.RecordBatch:
        i, j, a, b = (np.concatenate([h[c] for h in held]) for c in range(4))
        at = np.lexsort((b, a, j, i))
        i, j, a, b = i[at], j[at], a[at], b[at]
        begin = np.flatnonzero(np.r_[True, (i[1:] != i[:-1]) | (j[1:] != j[:-1])])
        end = np.r_[begin[1:], len(i)]
        packed = [pack(a[s:e], b[s:e]) for s, e in zip(begin, end, strict=True)]
        return pa.RecordBatch.from_arrays([pa.array(i[begin]), pa.array(j[begin]), pa.array(packed, pa.binary())], ["i", "j", "edges"])

    for batch in batches:
        held.append([batch.column(c).to_numpy() for c in range(4)])
        rows += batch.num_rows
        if rows >= PACKED:
            yield flush()
            held, rows = [], 0
    if rows:
        yield flush()


def count(a: np.ndarray, b: np.ndarray) -> int:
    """Triangles of distinct undirected edges. Every edge points to the end of greater degree, so no list of neighbours is long."""
    if len(a) < 3:
        return 0
    ids = np.sort(np.concatenate([a, b]))  # faster than unique, which hashes
    ids = ids[np.r_[True, ids[1:] != ids[:-1]]]
    n = len(ids)
    a, b = np.searchsorted(ids, a), np.searchsorted(ids, b)
    rank = np.empty(n, np.int64)
    rank[np.argsort(np.bincount(a, minlength=n) + np.bincount(b, minlength=n), kind="stable")] = np.arange(n)
    a, b = rank[a], rank[b]
    keys = np.sort(np.minimum(a, b) * n + np.maximum(a, b))
    del a, b
    low, high = np.divmod(keys, n)
    start = np.searchsorted(low, np.arange(n + 1))
    many = (start[1:] - start[:-1])[high]
    ends = np.cumsum(many)
    cuts = np.unique(np.r_[0, np.searchsorted(ends, np.arange(LOOKED_UP, ends[-1], LOOKED_UP)), len(keys)])
    found = 0
    for s, e in zip(cuts[:-1], cuts[1:], strict=True):
        here = many[s:e]
        total = int(here.sum())
        if not total:
            continue
        third = high[np.repeat(start[high[s:e]] - (np.cumsum(here) - here), here) + np.arange(total)]
        wanted = np.repeat(low[s:e] * n, here) + third
        near = keys[start[low[s]] : start[low[e - 1] + 1]]
        at = np.searchsorted(near, wanted)
        at[at == len(near)] = 0
        found += int((near[at] == wanted).sum())
    return found


def _counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    parts = [unpack(x.as_buffer()) for batch in batches for x in batch.column(0)]
    a, b = (np.concatenate([p[i] for p in parts]) if parts else np.zeros(0, np.int64) for i in range(2))
    parts.clear()
    yield pa.RecordBatch.from_arrays([pa.array([count(a, b)], pa.int64())], ["triangles"])


def colours(edges: int, per_task: int) -> int:
    """So many that the edges between three of them (six parts in colours squared) are ``per_task`` on average."""
    return 1 if edges <= per_task else max(3, math.ceil(math.sqrt(6 * edges / per_task)))


def _tasks(k: int, pairs: set[tuple[int, int]]) -> Iterator[tuple[int, list[tuple[int, int]]]]:
    """Weights and folders. Three colours have the triangles of three colours; two have those of one or both, so those of one colour,
    which k - 1 of them have, are taken off k - 2 times."""
    for three in combinations(range(k), 3):
        if pairs.issuperset(folders := list(combinations(three, 2))):
            yield 1, folders
    for i, j in combinations(range(k), 2):
        if folders := sorted(pairs & {(i, i), (i, j), (j, j)}):
            yield 1, folders
    if k != 2:
        yield from ((2 - k, [(i, i)]) for i in range(k) if (i, i) in pairs)


def triangles(g: Graph) -> DataFrame:
    """One row: triangles of the undirected graph."""
    spark = g.edges.sparkSession
    once, own = g.half, None
    if once is None:
        own = own_path(spark, "once")
        g.symmetric().edges.where("src < dst").select("src", "dst").write.parquet(own)
        once = spark.read.schema("src long, dst long").parquet(own)
    k = colours(once.count(), PER_TASK)
    colour = lambda v: F.pmod(F.xxhash64(v), F.lit(k)).cast("int")
    c, d = colour("src"), colour("dst")
    ends = once.select(F.least(c, d).alias("i"), F.greatest(c, d).alias("j"), F.when(c <= d, F.col("src")).otherwise(F.col("dst")).alias("a"), F.when(c <= d, F.col("dst")).otherwise(F.col("src")).alias("b"))
    at = own_path(spark, "packed")
    ends.mapInArrow(_chunks, "i int, j int, edges binary").repartition("i", "j").write.partitionBy("i", "j").option("compression", "zstd").parquet(at)
    if own:
        drop_path(spark, own)
    packed = spark.read.schema("edges binary, i int, j int").parquet(at)
    tasks = list(_tasks(k, {(r.i, r.j) for r in packed.select("i", "j").distinct().collect()}))  # k * k / 2 pairs at most

    def job(some: list[tuple[int, list[tuple[int, int]]]]) -> int:
        of = [packed.where(reduce(Column.__or__, ((F.col("i") == i) & (F.col("j") == j) for i, j in folders))).select("edges").coalesce(1) for _, folders in some]
        counted = [df.mapInArrow(_counts, "triangles long").select(F.col("triangles") * weight) for df, (weight, _) in zip(of, some, strict=True)]
        return reduce(DataFrame.union, counted).toDF("triangles").agg(F.sum("triangles")).first()[0]

    # a union of single partitions is one partition otherwise; two jobs, so that one is planned while the other runs
    with settings(spark, spark__sql__unionOutputPartitioning="false"), ThreadPoolExecutor(2) as pool:
        found = sum(pool.map(job, (tasks[t : t + TASKS] for t in range(0, len(tasks), TASKS))))
    drop_path(spark, at)
    return spark.createDataFrame([(found,)], "triangles long")
