"""A graph cut into vertex intervals and a grid of edge blocks.

Preprocessing as two passes over the edges: the first deals them to source partitions and counts the blocks, the second
writes the edges of dense blocks by destination partition and leaves those of sparse blocks by source partition; edges are
never sorted globally. ``fused`` counts first and writes once. With ``bucketed`` the two tables are hash-bucketed by q and by p, so
that no iteration moves an edge; small graphs are written as plain files, whose edges a plan may move.

Intervals are of equal width, or of about equal numbers of incoming edges (``how="mass"``), so that a few hubs make no task larger than others.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blockgraph.plans import costmodel
from blockgraph.sources.graphs import Graph
from blockgraph.storage import cut, drop_path, own_path

BUCKETED_FROM = 5_000_000


def interval(column, width: int):
    return F.expr(f"cast({column} div {width} as int)")


def assign_intervals(df: DataFrame, column: str, n: int, beta: int, name: str = "p") -> DataFrame:
    """Equal-width intervals of ids."""
    return df.withColumn(name, interval(column, width_of(n, beta)))


def width_of(n: int, beta: int) -> int:
    return max(1, -(-n // beta))


def mass_intervals(edges: DataFrame, beta: int, end: str = "dst") -> DataFrame:
    """p, first_id, last_id, xi: intervals of about equal numbers of edges at ``end``, for skewed degrees.

    Degrees are summed by id range first, so that no task sees more than its own range of ids. The ranges are written once, as bounds
    planned a second time can differ."""
    ranged = cut(edges.groupBy(F.col(end).alias("id")).count().repartitionByRange("id").withColumn("part", F.spark_partition_id()), "ranged")
    before = ranged.groupBy("part").agg(F.sum("count").alias("m")).withColumn("before", F.coalesce(F.sum("m").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    total = ranged.agg(F.sum("count").alias("total"))
    inside = Window.partitionBy("part").orderBy("id").rowsBetween(Window.unboundedPreceding, 0)
    mass = ranged.join(F.broadcast(before.drop("m")), "part").withColumn("mass", F.col("before") + F.sum("count").over(inside)).crossJoin(F.broadcast(total))  # one row
    p = F.expr(f"cast(least({beta} - 1, ((mass - count) * {beta}) div total) as int)")
    return mass.withColumn("p", p).groupBy("p").agg(F.min("id").alias("first_id"), F.max("id").alias("last_id"), F.sum("count").alias("xi"))


def blocked(edges: DataFrame, n: int, beta: int) -> DataFrame:
    """Edges with their block (p, q); a projection, nothing moves."""
    w = width_of(n, beta)
    return edges.withColumns({"p": interval("src", w), "q": interval("dst", w)})


def block_stats(edges: DataFrame, distinct: bool = False) -> DataFrame:
    """p, q, xi of the non-empty blocks; with ``distinct`` also their distinct sources s and destinations d."""
    more = [F.countDistinct("src").alias("s"), F.countDistinct("dst").alias("d")] if distinct else []
    return edges.groupBy("p", "q").agg(F.count(F.lit(1)).alias("xi"), *more)


class Intervals:
    """Which interval an id lies in: by width, or by the first ids of intervals."""

    def __init__(self, n: int, beta: int, firsts: list[int] | None = None):
        self.n, self.beta, self.width, self.firsts = n, beta, width_of(n, beta), firsts

    def place(self, df: DataFrame, column: str, name: str) -> DataFrame:
        """df with the interval of a column of ids. Bounds are met by cells of equal width, a broadcast of 5 * beta narrow rows."""
        if self.firsts is None:
            return df.withColumn(name, interval(column, self.width))
        cell = max(1, self.n // (4 * self.beta))
        ends = [*(f - 1 for f in self.firsts[1:]), self.n - 1]
        rows = [(c, f, e, p) for p, (f, e) in enumerate(zip(self.firsts, ends, strict=True)) for c in range(f // cell, e // cell + 1)]
        cells = df.sparkSession.createDataFrame(rows, f"_cell long, _first long, _last long, `{name}` int")
        met = df.join(F.broadcast(cells), (F.expr(f"{column} div {cell}") == F.col("_cell")) & F.col(column).between(F.col("_first"), F.col("_last")))
        return met.drop("_cell", "_first", "_last")

    def blocked(self, edges: DataFrame) -> DataFrame:
        return self.place(self.place(edges, "src", "p"), "dst", "q")

    def theta(self):
        """Vertices of interval p, as a Column over p."""
        if self.firsts is None:
            return F.lit(float(self.width))
        sizes = [b - a for a, b in zip(self.firsts, [*self.firsts[1:], self.n], strict=True)]
        return F.element_at(F.array(*(F.lit(float(x)) for x in sizes)), F.col("p") + 1)


def intervals(graph: Graph, beta: int, how: str = "width") -> Intervals:
    if how == "width":
        return Intervals(graph.n, beta)
    if how != "mass":
        raise ValueError(how)
    firsts = sorted(r.first_id for r in mass_intervals(graph.edges, beta).collect())  # beta rows
    return Intervals(graph.n, beta, [0, *firsts[1:]] if firsts else [0])


@dataclass
class Layout:
    graph: Graph
    beta: int
    intervals: Intervals
    blocks: DataFrame
    dense: DataFrame | None
    sparse: DataFrame | None
    degrees: DataFrame
    buckets: int
    bucketed: bool
    tables: list[str] = field(default_factory=list)

    @property
    def n(self) -> int:
        return self.graph.n

    def source_partition(self, p: int) -> DataFrame:
        return self._all().where(F.col("p") == p)

    def destination_partition(self, q: int) -> DataFrame:
        return self._all().where(F.col("q") == q)

    def _all(self) -> DataFrame:
        parts = [x for x in (self.dense, self.sparse) if x is not None]
        return parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])

    def vertices(self, by: str = "q") -> DataFrame:
        return self.intervals.place(self.graph.vertices, "id", by)

    def drop(self) -> None:
        """Takes the tables away, their files too."""
        drop_tables(self.blocks.sparkSession, self.tables)


def drop_tables(spark, tables: list[str]) -> None:
    """Takes away tables noted by ``save``."""
    for t in tables:
        spark.sql(f"DROP TABLE IF EXISTS {t.partition('|')[0]}")
        drop_path(spark, t.partition("|")[2])
    tables.clear()


def partition_pass(edges: DataFrame, where: Intervals, buckets: int) -> tuple[DataFrame, DataFrame]:
    """First pass: edges by source partition, written; and the block counts."""
    parts = cut(where.blocked(edges).repartition(buckets, "p"), "source-partitions")
    return parts, cut(block_stats(parts), "blocks")


def save(df: DataFrame, name: str, by: str, buckets: int, bucketed: bool, tables: list[str], order: str | None = None) -> DataFrame:
    """df written as a table of ``buckets`` buckets by a column, sorted inside by it and ``order`` if that is given, or as plain files."""
    spark = df.sparkSession
    if not bucketed:
        return cut(df, name)
    path, table = own_path(spark, name), f"{name}_{uuid.uuid4().hex}"
    out = df.repartition(buckets, by).write.bucketBy(buckets, by)
    (out.sortBy(by, order) if order else out).option("path", path).saveAsTable(table)
    tables.append(f"{table}|{path}")
    return spark.table(table)


def extract_pass(parts: DataFrame, modes: DataFrame, buckets: int, bucketed: bool, tables: list[str]) -> tuple[DataFrame | None, DataFrame | None]:
    """Second pass: edges of dense blocks by destination partition, the others by source partition. None: no such block."""
    kinds = {r[0] for r in modes.select("mode").distinct().collect()}
    named = parts.join(F.broadcast(modes.select("p", "q", "mode")), ["p", "q"])  # at most beta ** 2 narrow rows
    out = []
    for mode, by in (("dense", "q"), ("sparse", "p")):
        out.append(save(named.where(F.col("mode") == mode).drop("mode"), f"edges_{mode}", by, buckets, bucketed, tables, "src" if mode == "dense" else None) if mode in kinds else None)
    return out[0], out[1]


def build(graph: Graph, beta: int, mode: str = "two_mode", rule: str = "printed", phi: int = costmodel.PHI, psi: int = costmodel.PSI, fused: bool = True, bucketed: bool | None = None, buckets: int | None = None, how: str = "width") -> Layout:
    """The layout of a graph. mode: two_mode by the rule, or all blocks dense or streamed. how: intervals by width or by mass."""
    spark = graph.edges.sparkSession
    buckets = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
    where = intervals(graph, beta, how)
    if fused:
        parts = cut(where.blocked(graph.edges), "edges")
        stats = block_stats(parts, distinct=rule == "network")
    else:
        parts, stats = partition_pass(graph.edges, where, buckets)
        stats = block_stats(parts, distinct=True) if rule == "network" else stats
    modes = costmodel.classify(stats, beta, where.theta(), phi, psi, rule)
    if mode != "two_mode":
        modes = modes.withColumn("mode", F.lit("dense" if mode == "dense" else "sparse"))
    modes = cut(modes.select("p", "q", "xi", "crit", "mode"), "blocks")
    if bucketed is None:
        bucketed = (modes.agg(F.sum("xi")).first()[0] or 0) >= BUCKETED_FROM
    tables: list[str] = []
    dense, sparse = extract_pass(parts, modes, buckets, bucketed, tables)
    degrees = cut(parts.groupBy("src").agg(F.count(F.lit(1)).alias("outdeg")), "degrees")
    return Layout(graph, beta, where, modes, dense, sparse, degrees, buckets, bucketed, tables)
