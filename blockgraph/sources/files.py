"""Edge lists in files: Parquet, ORC, CSV, JSON with an explicit schema, and adjacency lines."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockgraph.storage import own_path


def roundtrip(df: DataFrame, kind: str, by: str | None = None) -> DataFrame:
    """df written in a format (parted by a column or not) and read with its own schema."""
    path = own_path(df.sparkSession, f"sink-{kind}")
    writer = df.write.format(kind)
    (writer.partitionBy(by) if by else writer).save(path)
    return df.sparkSession.read.schema(df.schema).format(kind).load(path)


def read_edges(spark: SparkSession, path: str, kind: str = "csv", weighted: bool = False, **options) -> DataFrame:
    """src, dst[, w] from files; the schema is fixed, so no pass over the data is made to guess it."""
    return spark.read.schema("src long, dst long" + (", w double" if weighted else "")).format(kind).options(**options).load(path)


def write_adjacency(edges: DataFrame) -> str:
    """Lines "source<tab>neighbour neighbour ..."; a source with very many neighbours has several lines."""
    path = own_path(edges.sparkSession, "adjacency")
    lists = edges.groupBy("src", F.pmod(F.xxhash64("dst"), F.lit(64)).alias("piece")).agg(F.array_join(F.transform(F.collect_list("dst"), lambda x: x.cast("string")), " ").alias("to"))
    lists.select(F.concat_ws("\t", F.col("src").cast("string"), "to").alias("value")).write.text(path)
    return path


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    parts = F.split("value", "\t")
    return spark.read.text(path).select(parts[0].cast("long").alias("src"), F.explode(F.split(parts[1], " ")).alias("dst")).select("src", F.col("dst").cast("long").alias("dst"))
