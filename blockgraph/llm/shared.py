"""Tables, shared intermediate results and size-checked broadcasts of the operators here."""

from __future__ import annotations

import gc

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockgraph.storage import own_path, shared_dir, table

__all__ = ["cut", "fresh", "shared_dir", "small", "table"]

#: Rows and bytes up to which a side of narrow rows may be broadcast; beyond them the same join is shuffled.
BROADCAST_ROWS = 1_000_000
BROADCAST_BYTES = 24 << 20


def cut(df: DataFrame, name: str, free: bool = False) -> DataFrame:
    """Writes df into the shared folder and reads it back: lineage ends there, so lost executors cost one read.

    The folder goes when the Spark application ends. free: df was made by a large shuffle, whose files nobody needs any more;
    they go with the driver's next garbage collection, which is asked for here (as spark.cleaner.periodicGC does)."""
    spark, path = df.sparkSession, own_path(df.sparkSession, name)
    df.write.option("compression", "zstd").parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    if free:
        del df
        gc.collect()
        spark.sparkContext._jvm.System.gc()
    return back


def fresh(name: str, taken: list[str]) -> str:
    """name, or name with as many underscores as make it differ from all taken ones."""
    while name.lower() in {t.lower() for t in taken}:
        name += "_"
    return name


def small(df: DataFrame, rows: int | None = None, width: int = 16, payload: str | None = None, each: int = 8) -> DataFrame:
    """df marked for broadcast if its measured size is within bounds, else df as it is (a shuffled join follows).

    df must be cheap to read (a result of cut); payload names an array column whose elements count ``each`` bytes too."""
    size = F.count(F.lit(1)).alias("n"), (F.coalesce(F.sum(F.size(payload)), F.lit(0)) if payload else F.lit(0)).alias("m")
    n, m = df.agg(*size).first()
    return F.broadcast(df) if n <= (rows or BROADCAST_ROWS) and n * width + each * m <= BROADCAST_BYTES else df
