"""One iteration over a layout: the dense path, the streamed path, and both by block.

Dense path. The destination interval stays; copies of source intervals (slices) go to the dense blocks that exist, by q, and
meet the edges that lie there already, both sides sorted by source, so that no task holds all slices of an interval in memory;
the fold by destination needs no further exchange.
Streamed path. Edges meet their source interval where they lie, by p; messages are folded by destination before they move,
then go to q and are folded again.
The two folds are gathered at the destination vertices, which lie by q as well.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blockgraph.plans.layout import Layout
from blockgraph.plans.program import VertexProgram


def zigzag(spark, beta: int) -> DataFrame:
    """step, q, p, reused: the order of blocks; every other column runs backwards, so a column starts with the interval that
    the one before ended with."""
    grid = spark.range(beta * beta).select((F.col("id") + 1).alias("step"), F.expr(f"cast(id div {beta} as int)").alias("q"), F.expr(f"cast(id % {beta} as int)").alias("k"))
    grid = grid.withColumn("p", F.when(F.col("q") % 2 == 0, F.col("k")).otherwise(beta - 1 - F.col("k")))
    return grid.withColumn("reused", F.coalesce(F.lag("p").over(Window.orderBy("step")) == F.col("p"), F.lit(False))).select("step", "q", "p", "reused")


def by(df: DataFrame, layout: Layout, column: str) -> DataFrame:
    """df by interval: bucketed tables lie so already."""
    return df if layout.bucketed else df.repartition(layout.buckets, column)


def _messages(rows: DataFrame, prog: VertexProgram, *keys: str) -> DataFrame:
    return rows.select(*keys, *(m.alias(a) for m, a in zip(prog.message, prog.accumulators, strict=True)))


def slices(layout: Layout, values: DataFrame) -> DataFrame:
    """Copies of source vertices, one for each dense block of their interval."""
    directory = layout.blocks.where("mode = 'dense'").select("p", "q")
    return values.join(F.broadcast(directory), "p")  # at most beta ** 2 pairs of integers


def dense(layout: Layout, values: DataFrame, prog: VertexProgram) -> DataFrame | None:
    """q, dst, acc...: folds over the dense blocks."""
    if layout.dense is None:
        return None
    moved = slices(layout, values).withColumnRenamed("id", "src").drop("p").repartition(layout.buckets, "q")
    edges = by(layout.dense.drop("p"), layout, "q")
    met = edges.hint("merge").join(moved, ["q", "src"])
    return _messages(met, prog, "q", "dst").groupBy("q", "dst").agg(*prog.fold(prog.accumulators))


def emit(layout: Layout, values: DataFrame, prog: VertexProgram, pre_combine: bool = True) -> DataFrame | None:
    """p, q, dst, acc...: valued edges of the sparse blocks, grouped by destination inside a source interval or not."""
    if layout.sparse is None:
        return None
    edges, here = by(layout.sparse, layout, "p"), by(values.withColumnRenamed("id", "src"), layout, "p")
    out = _messages(edges.join(here.hint("shuffle_hash"), ["p", "src"]), prog, "p", "q", "dst")
    return out.groupBy("p", "q", "dst").agg(*prog.fold(prog.accumulators)) if pre_combine else out


def fold(layout: Layout, messages: DataFrame, prog: VertexProgram) -> DataFrame:
    """q, dst, acc...: messages brought to their destination interval and folded."""
    return messages.drop("p").repartition(layout.buckets, "q").groupBy("q", "dst").agg(*prog.fold(prog.accumulators))


def two_mode(layout: Layout, values: DataFrame, prog: VertexProgram, pre_combine: bool = True) -> DataFrame:
    """values (id, p, outdeg, value columns) to new values with old_<name> beside them."""
    d, sent = dense(layout, values, prog), emit(layout, values, prog, pre_combine)
    s = fold(layout, sent, prog) if sent is not None else None
    here = by(values.withColumnRenamed("p", "q"), layout, "q")
    names = prog.accumulators
    for tag, part in (("d", d), ("s", s)):
        if part is not None:
            part = part.select("q", F.col("dst").alias("id"), *(F.col(a).alias(f"{a}_{tag}") for a in names))
            here = here.join(part.hint("shuffle_hash"), ["q", "id"], "left")
    if d is not None and s is not None:
        accs = prog.both([F.col(f"{a}_d") for a in names], [F.col(f"{a}_s") for a in names])
    elif d is None and s is None:
        accs = [F.lit(None).cast("double") for _ in names]
    else:
        accs = [F.col(f"{a}_{'d' if d is not None else 's'}") for a in names]
    here = here.withColumns(dict(zip(names, accs, strict=True)))
    kept = here.select(F.col("id"), F.col("q").alias("p"), "outdeg", *(F.col(c).alias(f"old_{c}") for c in prog.init), *(x.alias(c) for c, x in prog.finish.items()))
    return kept
