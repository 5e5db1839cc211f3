"""Streaming and user-defined-function keys."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from blockgraph.catalog.methods import blocks_sql, graph
from blockgraph.functions import udx
from blockgraph.plans import layout as lay
from blockgraph.registry import add, key
from blockgraph.sources.graphs import edges_cte, rmat_sql
from blockgraph.storage import cut, settings, table
from blockgraph.streaming import edges as st


def _n():
    return F.count(F.lit(1)).alias("n")


def _stamp(c: str):
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss")


_S = "strftime({0}, '%Y-%m-%d %H:%M:%S')"


@key("stream_tumbling", f"SELECT {_S.format("time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01')")} AS day, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf):
    out = st.event_stream(spark, sf).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(_n())
    return st.finish(out.select(_stamp("w.start").alias("day"), "event_type", "n"), "complete")


@key("stream_sliding", f"SELECT {_S.format('start')} AS start, count(*)::BIGINT AS n FROM (SELECT time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01') - k * INTERVAL 12 HOUR AS start FROM events, (SELECT unnest([0, 1]) AS k)) GROUP BY 1")
def stream_sliding(spark, sf):
    out = st.event_stream(spark, sf).groupBy(F.window("ts", "1 day", "12 hours").alias("w")).agg(_n())
    return st.finish(out.select(_stamp("w.start").alias("start"), "n"), "complete")


@key("stream_session", f"""SELECT user_id, {_S.format('min(ts)')} AS start, count(*)::BIGINT AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s""")
def stream_session(spark, sf):
    out = st.event_stream(spark, sf).groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(_n())
    return st.finish(out.select("user_id", _stamp("w.start").alias("start"), "n"), "complete")


@key("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, sf):
    return st.finish(st.event_stream(spark, sf).withWatermark("ts", "60 days").select("user_id", "event_type", "ts").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type"))


_LATE = "(SELECT ts, ntile(4) OVER (ORDER BY event_id) AS b FROM events)"


@key("stream_late", f"""WITH e AS {_LATE}, w AS (SELECT b, max(ts) OVER (ORDER BY b) - INTERVAL 1 DAY AS mark FROM (SELECT b, max(ts) AS ts FROM e GROUP BY b)),
k AS (SELECT e.ts, e.b, time_bucket(INTERVAL 1 DAY, e.ts, TIMESTAMP '1970-01-01') + INTERVAL 1 DAY AS stop FROM e LEFT JOIN w ON w.b = e.b - 1 WHERE w.mark IS NULL OR time_bucket(INTERVAL 1 DAY, e.ts, TIMESTAMP '1970-01-01') + INTERVAL 1 DAY > w.mark)
SELECT {_S.format("stop - INTERVAL 1 DAY")} AS day, count(*)::BIGINT AS n FROM k WHERE stop <= (SELECT max(mark) FROM w) GROUP BY stop""")
def stream_late(spark, sf):
    """Four batches by event id; rows whose day ended before the watermark that the batch before has set are dropped.

    With ``allowMultiple`` Spark would drop by the watermark of two batches before, as chained stateful operators need; here is one."""
    e = table(spark, sf, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    out = st.dealt_stream(spark, e, 4, "event_id").withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w")).agg(_n())
    with settings(spark, spark__sql__streaming__statefulOperator__allowMultiple="false"):
        return st.finish(out.select(_stamp("w.start").alias("day"), "n"))


@key("stream_static_join", "SELECT event_type, (user_id // 100)::INT AS block, count(*)::BIGINT AS n FROM events GROUP BY 1, 2")
def stream_static_join(spark, sf):
    blocks = cut(table(spark, sf, "events").select("user_id").distinct().withColumn("block", F.expr("cast(user_id div 100 as int)")), "user-blocks")
    return st.finish(st.event_stream(spark, sf).join(blocks, "user_id").groupBy("event_type", "block").agg(_n()), "complete")


@key("stream_interval_join", "SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def stream_interval_join(spark, sf):
    e = st.event_stream(spark, sf)
    c = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click_id"), F.col("ts").alias("c_ts")).withWatermark("c_ts", "1 hour")
    p = e.where("event_type = 'purchase'").select(F.col("user_id").alias("p_user"), F.col("event_id").alias("purchase_id"), F.col("ts").alias("p_ts")).withWatermark("p_ts", "1 hour")
    return st.finish(c.join(p, F.expr("user_id = p_user and p_ts >= c_ts and p_ts <= c_ts + interval 1 hour")).select("click_id", "purchase_id"))


_PQ = "(user_id // 50)::INT AS p, (json_extract_string(props, '$.k')::BIGINT // 25)::INT AS q"


def _block_counts(stream):
    return stream.select(F.expr("cast(user_id div 50 as int)").alias("p"), F.expr("cast(cast(get_json_object(props, '$.k') as long) div 25 as int)").alias("q")).groupBy("p", "q").agg(F.count(F.lit(1)).alias("xi"))


add("stream_block_counts", lambda spark, sf: st.latest(st.finish(_block_counts(st.event_stream(spark, sf)), "update"), "p", "q"), f"SELECT p, q, count(*)::BIGINT AS xi FROM (SELECT {_PQ} FROM events) GROUP BY 1, 2")


@key("stream_reclassify", f"SELECT p, q, count(*)::BIGINT AS xi FROM (SELECT {_PQ} FROM events) GROUP BY 1, 2 HAVING count(*) >= 60")
def stream_reclassify(spark, sf):
    """Blocks that become dense (60 edges or more) as edges arrive in three batches; each with its final count."""
    e = table(spark, sf, "events").select("event_id", "user_id", "props")
    rows = cut(st.finish(_block_counts(st.dealt_stream(spark, e, 3, "event_id")), "update"), "block-updates")
    crossed = rows.where("xi >= 60").groupBy("p", "q").agg(F.min("_epoch").alias("since"))
    return st.latest(rows, "p", "q").join(crossed, ["p", "q"]).select("p", "q", "xi")


@key("stream_state", "SELECT event_type, count(*)::BIGINT AS n, round(sum(value), 4) AS total FROM events GROUP BY 1")
def stream_state(spark, sf):
    e = table(spark, sf, "events").select("event_id", "event_type", "value")
    out = st.dealt_stream(spark, e, 3, "event_id").groupBy("event_type").applyInPandasWithState(st.count_states, "event_type string, n long, total double", "n long, total double", "update", GroupStateTimeout.NoTimeout)
    return st.latest(st.finish(out, "update"), "event_type").withColumn("total", F.round("total", 4))


# --- user-defined functions -------------------------------------------------------------------------------------------
add("udf_scalar", lambda spark, sf: table(spark, sf, "supplier").select("s_suppkey", udx.half_life("s_acctbal").alias("x")), "SELECT s_suppkey, s_acctbal / 2 AS x FROM supplier")
_B8 = f"WITH {blocks_sql('copart_thin', 8)}"
add("udf_arrow", lambda spark, sf: (lambda g: lay.block_stats(lay.blocked(g.edges, g.n, 8)))(graph(spark, sf, "copart_thin")).select(udx.block_code("p", "q").alias("code"), "xi"), f"{_B8} SELECT (p * 1000 + q)::BIGINT AS code, xi FROM b")
add("udaf_combine", lambda spark, sf: graph(spark, sf, "supply").edges.groupBy("src").agg(udx.fold_sum("w").alias("w")).select("src", F.round("w", 4).alias("w")), f"WITH {edges_cte('supply')} SELECT src, round(sum(w), 4) AS w FROM e GROUP BY src")


@key("udtf_zigzag", "SELECT (i + 1)::INT AS step, (i // 5)::INT AS q, (CASE WHEN (i // 5) % 2 = 0 THEN i % 5 ELSE 4 - i % 5 END)::INT AS p FROM range(25) t(i)")
def udtf_zigzag(spark, sf):
    spark.udtf.register("zigzag", udx.Zigzag)
    return spark.sql("SELECT * FROM zigzag(5)")


@key("udtf_rmat", rmat_sql(6, 3))
def udtf_rmat(spark, sf):
    spark.udtf.register("rmat_edges", udx.RmatEdges)
    return spark.sql("SELECT DISTINCT e.src, e.dst FROM range(0, 4) r, LATERAL rmat_edges(6, 7, cast(r.id * 48 as int), cast(r.id * 48 + 48 as int)) e")


def _rmat_edge_sql() -> str:
    return rmat_sql(6, 3).replace("SELECT DISTINCT", "SELECT i AS id,").replace("FROM (SELECT ", "FROM (SELECT i, ").replace("range(192) t(i)", "range((SELECT max(event_id) + 1 FROM events)) t(i)")


@key("datasource_rmat", f"SELECT src, dst, count(*)::BIGINT AS n, round(sum(value), 4) AS total FROM ({_rmat_edge_sql()}) JOIN events ON id = event_id GROUP BY 1, 2")
def datasource_rmat(spark, sf):
    """The events laid on a recursive-matrix graph from the generator source, an edge for each event id: events and their values by edge."""
    spark.dataSource.register(udx.RmatSource)
    e = table(spark, sf, "events").select("event_id", "value")
    last = e.agg(F.coalesce(F.max("event_id"), F.lit(-1))).first()[0]
    parts = max(4, spark.sparkContext.defaultParallelism)
    edges = spark.read.format("rmat").option("scale", 6).option("edges", last + 1).option("parts", parts).load()
    return e.join(edges, F.col("event_id") == F.col("id")).groupBy("src", "dst").agg(_n(), F.round(F.sum("value"), 4).alias("total"))


@key("kernel_arrow_block", f"WITH {edges_cte('hetero')} SELECT dst, round(sum(1.0::DOUBLE / (1 + src)) + 1e-9, 6) AS acc FROM e GROUP BY dst")
def kernel_arrow_block(spark, sf):
    g = graph(spark, sf, "hetero")
    edges = lay.blocked(g.edges, g.n, 16)
    slices = edges.select("q", "src").distinct().withColumn("x", 1.0 / (1 + F.col("src")))
    return udx.kernel_fold(edges.select("q", "src", "dst"), slices).select("dst", F.round(F.col("acc") + 1e-9, 6).alias("acc"))
