"""Stand-ins for the systems compared with: the same PageRank or components from different physical plans.

What is known of the systems is little (properties only); each stand-in keeps its stated property and nothing else."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockgraph.plans import layout as lay
from blockgraph.plans import metrics
from blockgraph.sources.graphs import Graph
from blockgraph.storage import cut


def _degrees(g: Graph) -> DataFrame:
    return g.edges.groupBy("src").agg(F.count(F.lit(1)).alias("outdeg"))


def _finish(g: Graph, sums: DataFrame) -> DataFrame:
    return g.vertices.join(sums, "id", "left").select("id", (F.lit(0.15) + 0.85 * F.coalesce("acc", F.lit(0.0))).alias("rank"))


def naive(g: Graph, iters: int) -> DataFrame:
    """Plain joins and one aggregate; no blocks."""
    e = cut(g.edges.join(_degrees(g), "src").select("src", "dst", "outdeg"), "naive")
    v = g.vertices.withColumn("rank", F.lit(1.0))
    for _ in range(iters):
        v = cut(_finish(g, e.join(v.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("rank") / F.col("outdeg")).alias("acc"))), "naive")
    return v


def sorted_shards(g: Graph, iters: int, beta: int = 16) -> DataFrame:
    """B1: edges in shards by destination interval, sorted by source; values travel on the edges, which are all rewritten each time."""
    e = lay.blocked(g.edges.join(_degrees(g), "src"), g.n, beta).withColumn("value", F.lit(1.0)).select("src", "dst", "outdeg", "value", "q")
    e = cut(e.repartitionByRange("q", "src").sortWithinPartitions("q", "src"), "shards")
    v = None
    for _ in range(iters):
        v = cut(_finish(g, e.groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("value") / F.col("outdeg")).alias("acc"))), "shard-values")
        e = cut(e.drop("value").join(v.select(F.col("id").alias("src"), F.col("rank").alias("value")), "src").select("src", "dst", "outdeg", "value", "q").repartitionByRange("q", "src").sortWithinPartitions("q", "src"), "shards")
    return v


def _scattered(e: DataFrame, v: DataFrame) -> DataFrame:
    return e.join(v.withColumnRenamed("id", "src"), "src").select(F.col("dst").alias("id"), (F.col("rank") / F.col("outdeg")).alias("u"))


def scatter_gather(g: Graph, iters: int) -> DataFrame:
    """B2: every iteration reads all edges, writes one update per edge, reads all updates; nothing is combined before."""
    e = cut(g.edges.join(_degrees(g), "src").select("src", "dst", "outdeg"), "edges")
    v = g.vertices.withColumn("rank", F.lit(1.0))
    for _ in range(iters):
        v = cut(_finish(g, cut(_scattered(e, v), "updates").groupBy("id").agg(F.sum("u").alias("acc"))), "gathered")
    return v


def scatter_gather_scans(g: Graph) -> int:
    """File scans of one iteration of B2: edges and values to scatter, updates to gather."""
    e = cut(g.edges.join(_degrees(g), "src").select("src", "dst", "outdeg"), "edges")
    sent = _scattered(e, cut(g.vertices.withColumn("rank", F.lit(1.0)), "gathered"))
    return metrics.scans(sent) + metrics.scans(cut(sent, "updates").groupBy("id").agg(F.sum("u").alias("acc")))


def _symmetric(g: Graph) -> DataFrame:
    return g.symmetric().edges.select("src", "dst")


def wcc_scatter_gather(g: Graph) -> DataFrame:
    """B2's components: smallest labels, iterated; every iteration writes and reads one update per edge."""
    e, v, moved = cut(_symmetric(g), "edges"), cut(g.vertices.withColumn("label", F.col("id")), "labels"), 1
    while moved:
        updates = cut(e.join(v.withColumnRenamed("id", "src"), "src").select(F.col("dst").alias("id"), F.col("label").alias("u")), "updates")
        new = v.join(updates.groupBy("id").agg(F.min("u").alias("u")), "id", "left").select("id", F.least("label", "u").alias("label"), F.col("label").alias("old"))
        new = cut(new, "labels")
        moved = new.where("label <> old").limit(1).count()
        v = new.drop("old")
    return v


def wcc_dedicated(g: Graph) -> DataFrame:
    """B4's components: a plan for this algorithm alone, edges kept in memory as far as it goes."""
    e = _symmetric(g).persist()
    v, moved = cut(g.vertices.withColumn("label", F.col("id")), "labels"), 1
    while moved:
        least = e.join(v.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id")).agg(F.min("label").alias("u"))
        new = cut(v.join(least, "id", "left").select("id", F.least("label", "u").alias("label"), F.col("label").alias("old")), "labels")
        moved = new.where("label <> old").limit(1).count()
        v = new.drop("old")
    e.unpersist()
    return v


def adjacency_index(g: Graph, iters: int, piece: int = 4096) -> DataFrame:
    """B3: neighbour lists by source (hubs in pieces, so no list is long), exploded each time."""
    e = g.edges.withColumn("piece", F.pmod(F.xxhash64("dst"), F.lit(1_000_000)) % F.lit(max(1, g.n // piece)))
    lists = cut(e.groupBy("src", "piece").agg(F.collect_list("dst").alias("to")).join(_degrees(g), "src"), "index")
    v = g.vertices.withColumn("rank", F.lit(1.0))
    for _ in range(iters):
        sent = lists.join(v.withColumnRenamed("id", "src"), "src").select(F.explode("to").alias("id"), (F.col("rank") / F.col("outdeg")).alias("u"))
        v = cut(_finish(g, sent.groupBy("id").agg(F.sum("u").alias("acc"))), "indexed")
    return v


def cached_dedicated(g: Graph, iters: int) -> DataFrame:
    """B4: a plan for this algorithm alone, edges kept in memory as far as it goes, all iterations one lineage."""
    e = g.edges.join(_degrees(g), "src").select("src", "dst", "outdeg").persist()
    v = g.vertices.withColumn("rank", F.lit(1.0))
    for _ in range(iters):
        v = _finish(g, e.join(v.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("rank") / F.col("outdeg")).alias("acc")))
    out = cut(v, "dedicated")
    e.unpersist()
    return out


def uniform_grid(g: Graph, iters: int, beta: int = 16) -> DataFrame:
    """B5: a two-dimensional grid of blocks, each folded by itself; the parts of a column are then added up. No block is classified."""
    e = cut(lay.blocked(g.edges.join(_degrees(g), "src"), g.n, beta).repartition("p", "q"), "grid")
    v = g.vertices.withColumn("rank", F.lit(1.0))
    for _ in range(iters):
        here = lay.assign_intervals(v, "id", g.n, beta).withColumnRenamed("id", "src")
        blocks = e.join(here, ["p", "src"]).groupBy("p", "q", "dst").agg(F.sum(F.col("rank") / F.col("outdeg")).alias("part"))
        v = cut(_finish(g, blocks.groupBy(F.col("dst").alias("id")).agg(F.sum("part").alias("acc"))), "grid-values")
    return v
