"""Numbering and streams over more rows than the sample of range bounds holds, and with equal gaps."""

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from blockgraph.plans import layout as lay
from blockgraph.sources.graphs import dense_ids
from blockgraph.storage import settings
from tests.oracle_check import compare, connect

KEYS = ["stream_block_counts", "stream_dedup", "stream_interval_join", "stream_late", "stream_reclassify", "stream_session", "stream_sliding", "stream_state", "stream_static_join", "stream_tumbling"]


@pytest.fixture(autouse=True)
def ranges(spark):
    """Small partitions stay apart, as large ones do."""
    with settings(spark, spark__sql__adaptive__coalescePartitions__enabled="false"):
        yield


@pytest.fixture(scope="module")
def grown(spark, tmp_path_factory):
    """events 60 times, with shifted keys."""
    to = tmp_path_factory.mktemp("grown")
    e = spark.read.parquet("/root/testdata/sf0.001/events.parquet")
    size, users = e.count(), e.agg(F.max("user_id") + 1).first()[0]
    e = e.crossJoin(spark.range(60)).withColumns({"event_id": F.col("event_id") + F.col("id") * size, "user_id": F.col("user_id") + F.col("id") * users}).drop("id")
    e.coalesce(1).write.parquet(f"{to}/events.parquet")
    return to


def test_ids_have_no_gaps(spark):
    df = spark.range(300_000, numPartitions=8).select(F.xxhash64("id").alias("k"), F.repeat(F.lit("x"), (F.col("id") % 300).cast("int")).alias("pad"))
    got = dense_ids(df, ["k"]).agg(F.min("id"), F.max("id"), F.count_distinct("id")).first()
    assert tuple(got) == (0, 299_999, 300_000)


def test_mass_intervals_hold_all_edges(spark):
    edges = spark.range(400_000, numPartitions=8).select((F.xxhash64("id") % 150_000).alias("src"), F.col("id").alias("dst"))
    rows = sorted(lay.mass_intervals(edges, 16, "src").collect())
    assert sum(r.xi for r in rows) == 400_000 and all(a.last_id < b.first_id for a, b in zip(rows, rows[1:]))
    assert max(r.xi for r in rows) < 1.1 * 400_000 / 16


@pytest.mark.parametrize("key", KEYS)
def test_streams_of_many_rows(spark, grown, key):
    con = connect("/root/testdata/sf0.001")
    con.sql(f"CREATE OR REPLACE VIEW events AS SELECT * FROM '{grown}/events.parquet/*.parquet'")
    assert compare(entry.queries()[key], entry.oracle_sql()[key], spark, con, str(grown)).startswith("ok")
