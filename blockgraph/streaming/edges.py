"""Events and edges as streams: read as a file stream, run until all input is taken (AvailableNow), results in the shared folder.

``ts`` is cast to a timestamp first, as watermarks need. Append mode emits windows only once the watermark has passed them."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockgraph.sources.graphs import dense_ids
from blockgraph.storage import cut, own_path, table


FILE_ROWS = 1_000_000


def event_stream(spark: SparkSession, sf: str, batches: int = 4) -> DataFrame:
    """events in the order of their times, as a stream of several micro-batches, ts as a timestamp."""
    events = table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return dealt_stream(spark, events, batches)


def dealt_stream(spark: SparkSession, events: DataFrame, batches: int, order: str = "ts") -> DataFrame:
    """A table as a stream of ``batches`` micro-batches of equal size in the order of a column, each of as many files as it needs.

    Rows are numbered by ranges, so no task sees them all."""
    path = own_path(spark, "stream-input")
    numbered = cut(dense_ids(events, [order], "_row"), "stream-rows")
    rows = numbered.count()
    small, more = divmod(rows, batches)  # the first ones have one row more
    edge = more * (small + 1)
    batch = F.when(F.col("_row") < edge, F.floor(F.col("_row") / (small + 1))).otherwise(more + F.floor((F.col("_row") - edge) / max(small, 1)))
    files = max(1, -(-(small + 1) // FILE_ROWS))
    for b in range(batches):  # files get ascending times, which the file source goes by
        numbered.where(batch == b).drop("_row").repartition(files).write.mode("append").parquet(path)
    return spark.readStream.schema(events.schema).option("maxFilesPerTrigger", files).parquet(path)


def finish(stream: DataFrame, mode: str = "append", collect: Callable[[DataFrame, int], None] | None = None) -> DataFrame:
    """Runs a stream over all its input and gives the rows it emitted.

    append: all emitted rows. complete: the last result. update: for every key of the result the last row (see ``latest``)."""
    spark = stream.sparkSession
    out, checkpoint = own_path(spark, "stream-out"), own_path(spark, "stream-state")

    def put(df: DataFrame, epoch: int) -> None:
        df = df.withColumn("_epoch", F.lit(epoch).cast("long"))
        df.write.mode("overwrite" if mode == "complete" else "append").parquet(out)

    query = stream.writeStream.outputMode(mode).foreachBatch(collect or put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    if collect:
        return spark.createDataFrame([], stream.schema)
    schema = stream.schema.add("_epoch", "long")
    try:
        rows = spark.read.schema(schema).parquet(out)
    except Exception as e:  # nothing was emitted
        if "PATH_NOT_FOUND" not in str(e):
            raise
        rows = spark.createDataFrame([], schema)
    return rows if mode == "update" else rows.drop("_epoch")


def latest(rows: DataFrame, *keys: str) -> DataFrame:
    """Of update-mode rows the last one of each key."""
    others = [c for c in rows.columns if c not in keys and c != "_epoch"]
    best = rows.groupBy(*keys).agg(F.max(F.struct("_epoch", *others)).alias("r"))
    return best.select(*keys, *(F.col(f"r.{c}").alias(c) for c in others))


def count_states(key: str, rows: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
    """Running count and sum of a key, kept from batch to batch."""
    n, total = state.get if state.exists else (0, 0.0)
    for part in rows:
        n, total = n + len(part), total + float(part["value"].sum())
    state.update((n, total))
    yield pd.DataFrame({"event_type": [key[0]], "n": [n], "total": [total]})
