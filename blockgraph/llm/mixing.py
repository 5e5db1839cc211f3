"""Mixing sources to target weights by capped water-filling, DataFrame operations only.

Every source shall get the share of all words that its weight asks for, but no more than ``epochs`` times what it has; the
excess goes to the others by weight, again and again, until none is above. Sorted by words per weight the clamped sources
are a prefix, so the fixed point needs one pass over the table of sources.

A source's target is reached by whole repetitions of all its documents and one more repetition of some: documents in the
order of a seeded hash until the words are enough, the last one in part. Running sums are first taken over hash bins (so a
source with a third of all rows is summed in parallel), and row by row only in the bin where the sum is reached.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from blockgraph.llm.shared import cut, small

WORD = r"[^\x20\x09-\x0D]+"
EPOCHS = 3
CYCLE = 3
SEED = "mix-1"
BIN_BITS = 10


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def draw(key: Column, seed: str) -> Column:
    """60 seeded pseudo-random bits of a key, the same in every run and engine."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(seed + ":"), F.coalesce(key.cast("string"), F.lit("")))), 1, 15), 16, 10).cast("long")


def cyclic_weights(sources: DataFrame, cycle: int = CYCLE) -> DataFrame:
    """Weights 1, 2 ... cycle, repeating, by the sources' code points, null last. One row per source."""
    return sources.withColumn("weight", ((F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1) % cycle + 1).cast("long"))


def water_fill(sources: DataFrame, epochs: int = EPOCHS) -> DataFrame:
    """(source, source_size, weight) to these and ``target`` (double); the targets add up to the sum of all sizes.

    No source, or sources without words, give no rows or targets of zero."""
    order = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    before, every = order.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    left = sources.withColumn("cap", F.col("source_size") * epochs)
    left = left.withColumns({
        "rest": F.sum("source_size").over(every) - F.coalesce(F.sum("cap").over(before), F.lit(0)),
        "weights": F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0)),
        "rank": F.row_number().over(order),
    })
    level = F.col("rest").cast("double") / F.col("weights")
    free = F.col("cap") >= level * F.col("weight")
    left = left.withColumn("first_free", F.min(F.when(free, F.struct("rank", level.alias("level")))).over(every))
    kept = F.when(F.col("rank") < F.coalesce(F.col("first_free.rank"), F.lit(2**31 - 1)), F.col("cap").cast("double"))
    return left.select("source", "source_size", "weight", F.coalesce(kept, F.col("first_free.level") * F.col("weight")).alias("target"))


def mix(docs: DataFrame, epochs: int = EPOCHS, seed: str = SEED, weights=cyclic_weights, carry: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, source, size, source_size, target, taken of each row of docs (doc_id, source, text), and its columns named in carry.

    Null texts have size 0 and null sources form one source; a null doc_id draws like an empty one. Repeated rows are taken
    like any others. Each source's taken words add up to its target rounded; none exceeds epochs times its size."""
    if clash := {c.lower() for c in carry} & {"doc_id", "source", "size", "source_size", "target", "taken"}:
        raise ValueError(f"{sorted(clash)} are columns of the result")
    row = F.struct(*(docs[c] for c in carry)) if carry else F.lit(None).cast("string")
    sized = docs.select("doc_id", "source", word_count(docs["text"]).alias("size"), draw(docs["doc_id"], seed).alias("u"), row.alias("row"))
    sized = cut(sized.withColumn("bin", F.shiftright("u", 60 - BIN_BITS).cast("int")), "mix-sizes")
    bins = sized.groupBy("source", "bin").agg(F.sum("size").alias("words"))
    goals = water_fill(weights(bins.groupBy("source").agg(F.sum("words").alias("source_size"))), epochs)
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    goals = goals.withColumn("whole", whole).withColumn("more", F.greatest(F.round("target").cast("long") - F.col("whole") * F.col("source_size"), F.lit(0)))
    same = F.col("a.source").eqNullSafe(F.col("b.source"))
    upto = Window.partitionBy("a.source").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    reached = bins.alias("a").join(F.broadcast(goals.alias("b")), same).withColumn("below", F.coalesce(F.sum("words").over(upto), F.lit(0)))
    reached = reached.where((F.col("below") <= F.col("more")) & (F.col("more") < F.col("below") + F.col("words")))
    plan = goals.alias("a").join(reached.select("b.source", F.col("bin").alias("last_bin"), "below").alias("b"), same, "left")
    plan = cut(plan.select(F.col("a.source").alias("source"), "source_size", "target", "whole", "more", F.coalesce("last_bin", F.lit(2**BIN_BITS)).alias("last_bin"), F.coalesce("below", F.lit(0)).alias("below")), "mix-plan")
    each = sized.alias("a").join(small(plan.alias("b"), width=64), same).select("a.doc_id", "a.source", "size", "u", "bin", "source_size", "target", "whole", "more", "last_bin", "below", "row")
    plain = each.where(F.col("bin") != F.col("last_bin")).withColumn("extra", F.when(F.col("bin") < F.col("last_bin"), F.col("size")).otherwise(0))
    run = Window.partitionBy("source").orderBy("u", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    edge = each.where(F.col("bin") == F.col("last_bin"))
    at = F.col("below") + F.coalesce(F.sum("size").over(run), F.lit(0))
    edge = edge.withColumn("extra", F.least("size", F.greatest(F.col("more") - at, F.lit(0))))
    out = plain.unionByName(edge)
    return out.select("doc_id", "source", "size", "source_size", "target", (F.col("whole") * F.col("size") + F.col("extra")).cast("long").alias("taken"), *(F.col(f"row.{c}").alias(c) for c in carry))


#: The same rows by one plain window, for DuckDB; {docs} is the relation.
MIX_SQL = rf"""
WITH sized AS (SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
    ('0x' || substr(md5('{SEED}:' || coalesce(doc_id::VARCHAR, '')), 1, 15))::BIGINT AS u FROM {{docs}}),
src AS (SELECT source, sum(size)::BIGINT AS source_size FROM sized GROUP BY source),
wt AS (SELECT *, ((row_number() OVER (ORDER BY source NULLS LAST) - 1) % {CYCLE} + 1)::BIGINT AS weight, source_size * {EPOCHS} AS cap FROM src),
lv AS (SELECT *, row_number() OVER o AS rk,
    ((sum(source_size) OVER ())::BIGINT - coalesce((sum(cap) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))::BIGINT, 0))::DOUBLE
    / ((sum(weight) OVER ())::BIGINT - coalesce((sum(weight) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))::BIGINT, 0)) AS level
    FROM wt WINDOW o AS (ORDER BY cap / weight, source NULLS LAST)),
fr AS (SELECT coalesce(min(rk) FILTER (WHERE cap >= level * weight), 2147483647) AS r FROM lv),
tg AS (SELECT source, source_size, CASE WHEN rk < r THEN cap::DOUBLE ELSE (SELECT level FROM lv WHERE rk = r) * weight END AS target FROM lv, fr),
pl AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size) ELSE 0 END::BIGINT AS whole FROM tg),
cu AS (SELECT s.doc_id, s.size, p.source_size, p.target, p.whole, greatest(round(p.target)::BIGINT - p.whole * p.source_size, 0) AS more,
    coalesce((sum(s.size) OVER (PARTITION BY s.source ORDER BY s.u, s.doc_id NULLS FIRST, s.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))::BIGINT, 0) AS below
    FROM sized s JOIN pl p ON s.source IS NOT DISTINCT FROM p.source)
SELECT doc_id, size, source_size, target, (whole * size + least(size, greatest(more - below, 0)))::BIGINT AS taken FROM cu
"""
