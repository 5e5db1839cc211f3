"""Relational operators around the methods: sources, joins, aggregates, windows, sorts, sets, functions, SQL."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from blockgraph.catalog.methods import blocks_sql, graph, modes, modes_sql, pagerank_sql
from blockgraph.functions import vectors
from blockgraph.operators import algorithms as alg
from blockgraph.operators import joins
from blockgraph.plans import layout as lay
from blockgraph.registry import add, key
from blockgraph.sources import files
from blockgraph.sources.graphs import edges_cte
from blockgraph.storage import cut, table

N = lambda: F.count(F.lit(1))  # noqa: E731  (Columns need a session, so none is made at import)


# --- sources and sinks ------------------------------------------------------------------------------------------------
_THIN = f"WITH {edges_cte('copart_thin')} SELECT src, dst FROM e"
add("src_parquet", lambda spark, sf: graph(spark, sf, "copart_thin").edges.select("src", "dst"), _THIN)
for _f in ("csv", "json", "orc"):
    add(f"src_{_f}_roundtrip", lambda spark, sf, f=_f: files.roundtrip(graph(spark, sf, "copart_thin").edges.select("src", "dst"), f), _THIN)
add("src_adjacency", lambda spark, sf: files.read_adjacency(spark, files.write_adjacency(graph(spark, sf, "copart_thin").edges)), _THIN)


@key("sink_partitioned_roundtrip", f"WITH {modes_sql('hetero')} SELECT mode, count(*)::BIGINT AS blocks, sum(xi)::BIGINT AS edges FROM mm GROUP BY mode")
def sink_partitioned(spark, sf):
    return files.roundtrip(modes(spark, sf, "hetero").select("p", "q", "xi", "mode"), "parquet", by="mode").groupBy("mode").agg(N().alias("blocks"), F.sum("xi").alias("edges"))


# --- joins ------------------------------------------------------------------------------------------------------------
@key("join_broadcast", f"WITH {modes_sql('hetero')} SELECT mode, count(*)::BIGINT AS edges FROM g JOIN mm USING (p, q) GROUP BY mode")
def join_broadcast(spark, sf):
    g = graph(spark, sf, "hetero")
    return lay.blocked(g.edges, g.n, 128).join(F.broadcast(modes(spark, sf, "hetero").select("p", "q", "mode")), ["p", "q"]).groupBy("mode").agg(N().alias("edges"))  # at most beta ** 2 rows


add("join_sortmerge", lambda spark, sf: table(spark, sf, "lineitem").hint("merge").join(table(spark, sf, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey").agg(F.countDistinct("l_partkey").alias("parts")), "SELECT o_custkey, count(DISTINCT l_partkey)::BIGINT AS parts FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
add("join_shuffle_hash", lambda spark, sf: table(spark, sf, "lineitem").join(table(spark, sf, "part").hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(N().alias("lines")), "SELECT p_brand, count(*)::BIGINT AS lines FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")


@key("join_theta", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def join_theta(spark, sf):
    n = table(spark, sf, "nation")
    a, b = n.select("n_regionkey", F.col("n_nationkey").alias("ka"), F.col("n_name").alias("a")), n.select("n_regionkey", F.col("n_nationkey").alias("kb"), F.col("n_name").alias("b"))
    return a.join(b, "n_regionkey").where("ka < kb").select("a", "b")


@key("join_range_interval", f"""WITH {edges_cte('hetero')}, d AS (SELECT dst AS id, count(*) AS c FROM e GROUP BY 1), m AS (SELECT id, (sum(c) OVER (ORDER BY id))::BIGINT - c AS below, (SELECT count(*) FROM e) AS total FROM d),
b AS (SELECT least(15, below * 16 // total)::INT AS p, min(id) AS lo, max(id) AS hi FROM m GROUP BY 1) SELECT p, count(*)::BIGINT AS sources FROM (SELECT DISTINCT src FROM e) s JOIN b ON s.src BETWEEN b.lo AND b.hi GROUP BY p""")
def join_range(spark, sf):
    g = graph(spark, sf, "hetero")
    bounds = lay.mass_intervals(g.edges, 16).select("p", F.col("first_id").alias("lo"), F.col("last_id").alias("hi"))
    return joins.range_join(g.edges.select("src").distinct(), bounds, "src", "lo", "hi", width=max(1, g.n // 64)).groupBy("p").agg(N().alias("sources"))


_ASOF = """SELECT event_id, view_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS view_id FROM events) WHERE event_type = 'purchase'"""


@key("join_asof", _ASOF)
def join_asof(spark, sf):
    e = table(spark, sf, "events").select("user_id", "ts", "event_id", "event_type")
    found = joins.asof_join(e.where("event_type = 'purchase'"), e.where("event_type = 'view'").withColumnRenamed("event_id", "view_id"), "user_id", "ts", "event_id", "view_id")
    return found.select("event_id", "view_id")


_TYPES = "SELECT event_type, count(*) AS c FROM events GROUP BY 1"


@key("join_interval", "SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def join_interval(spark, sf):
    e = table(spark, sf, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"), "event_id", "event_type")
    c, p = e.where("event_type = 'click'").select("user_id", F.col("ts").alias("c_ts"), F.col("event_id").alias("click_id")), e.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("p_ts"), F.col("event_id").alias("purchase_id"))
    return joins.interval_join(c, p, "user_id", "c_ts", "p_ts", 3600).select("click_id", "purchase_id")


_IN = "(SELECT dst AS id, count(*)::BIGINT AS c FROM e GROUP BY 1)"


def _in(spark, sf):
    return graph(spark, sf, "placed").edges.groupBy(F.col("dst").alias("id")).agg(N().alias("c"))


add("join_left", lambda spark, sf: graph(spark, sf, "placed").vertices.join(_in(spark, sf), "id", "left").select("id", "c"), f"WITH {edges_cte('placed')} SELECT v.id, c FROM v LEFT JOIN {_IN} i USING (id)")
add("join_full", lambda spark, sf: graph(spark, sf, "placed").edges.groupBy(F.col("src").alias("id")).agg(N().alias("o")).join(_in(spark, sf), "id", "full").select("id", "o", "c"), f"WITH {edges_cte('placed')} SELECT coalesce(a.id, b.id) AS id, o, c FROM (SELECT src AS id, count(*)::BIGINT AS o FROM e GROUP BY 1) a FULL JOIN {_IN} b ON a.id = b.id")
add("join_semi", lambda spark, sf: (lambda g: g.vertices.join(g.edges.select(F.col("src").alias("id")), "id", "left_semi"))(graph(spark, sf, "hetero")), f"WITH {edges_cte('hetero')} SELECT id FROM v WHERE id IN (SELECT src FROM e)")
add("join_anti_dangling", lambda spark, sf: (lambda g: g.vertices.join(g.edges.select(F.col("src").alias("id")), "id", "left_anti"))(graph(spark, sf, "hetero")), f"WITH {edges_cte('hetero')} SELECT id FROM v WHERE id NOT IN (SELECT src FROM e)")
add("join_cross", lambda spark, sf: table(spark, sf, "region").select("r_name").crossJoin(F.broadcast(spark.createDataFrame([(b,) for b in (1, 4, 16)], "beta int"))), "SELECT r_name, beta FROM region, (SELECT unnest([1, 4, 16])::INT AS beta)")
add("join_self_copart", lambda spark, sf: graph(spark, sf, "copart").edges.where("src < dst and w >= 2").select("src", "dst", "w"), f"WITH {edges_cte('copart')} SELECT src, dst, w FROM e WHERE src < dst AND w >= 2")


@key("join_lateral_topk", f"WITH {edges_cte('supply')} SELECT src, dst, w FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) AS r FROM e) WHERE r <= 3")
def join_lateral_topk(spark, sf):
    g = graph(spark, sf, "supply")
    top = g.edges.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("w"), "dst"))).where("r <= 3").groupBy("src").agg(F.sort_array(F.collect_list(F.struct("r", "dst", "w"))).alias("best"))
    return g.edges.select("src").distinct().alias("s").join(top, "src").lateralJoin(spark.tvf.explode(F.col("best").outer()).toDF("b")).select("src", "b.dst", "b.w")


add("join_salted", lambda spark, sf: joins.salted_join(graph(spark, sf, "hetero").edges, graph(spark, sf, "hetero").edges.groupBy(F.col("src").alias("dst")).agg(N().alias("out")), "dst", 16).groupBy("dst").agg(N().alias("ins"), F.max("out").alias("out")), f"WITH {edges_cte('hetero')} SELECT dst, count(*)::BIGINT AS ins, max(c)::BIGINT AS out FROM e JOIN (SELECT src AS k, count(*) AS c FROM e GROUP BY 1) ON dst = k GROUP BY dst")

# --- aggregates -------------------------------------------------------------------------------------------------------
E = lambda n: lambda spark, sf: graph(spark, sf, n).edges
_E = {n: f"WITH {edges_cte(n)}" for n in ("hetero", "supply", "copart_thin", "purchase", "usage", "placed", "copart")}
add("agg_degree", lambda spark, sf: E("supply")(spark, sf).groupBy("src").agg(N().alias("parts"), F.sum("w").alias("quantity"), F.min("dst").alias("low"), F.max("dst").alias("high")), f"{_E['supply']} SELECT src, count(*)::BIGINT AS parts, sum(w) AS quantity, min(dst) AS low, max(dst) AS high FROM e GROUP BY src")
add("agg_distinct", lambda spark, sf: table(spark, sf, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users")), "SELECT event_type, count(DISTINCT user_id)::BIGINT AS users FROM events GROUP BY 1")
add("agg_having", lambda spark, sf: E("hetero")(spark, sf).groupBy("dst").agg(N().alias("c")).where("c >= 40"), f"{_E['hetero']} SELECT dst, count(*)::BIGINT AS c FROM e GROUP BY dst HAVING count(*) >= 40")
add("agg_stddev", lambda spark, sf: table(spark, sf, "orders").groupBy("o_orderpriority").agg(F.round(F.stddev("o_totalprice"), 4).alias("sd"), F.round(F.avg("o_totalprice"), 4).alias("mean")), "SELECT o_orderpriority, round(stddev(o_totalprice), 4) AS sd, round(avg(o_totalprice), 4) AS mean FROM orders GROUP BY 1")
_B = lambda spark, sf: (lambda g: lay.block_stats(lay.blocked(g.edges, g.n, 8)))(graph(spark, sf, "copart_thin"))
_BS = f"WITH {blocks_sql('copart_thin', 8)}"
add("agg_rollup_blocks", lambda spark, sf: _B(spark, sf).rollup("p", "q").agg(F.sum("xi").alias("xi"), F.grouping_id().cast("int").alias("gid")), f"{_BS} SELECT p, q, sum(xi)::BIGINT AS xi, grouping(p, q)::INT AS gid FROM b GROUP BY ROLLUP (p, q)")
add("agg_cube_blocks", lambda spark, sf: _B(spark, sf).cube("p", "q").agg(F.sum("xi").alias("xi"), F.grouping_id().cast("int").alias("gid")), f"{_BS} SELECT p, q, sum(xi)::BIGINT AS xi, grouping(p, q)::INT AS gid FROM b GROUP BY CUBE (p, q)")
add("agg_grouping_sets", lambda spark, sf: _B(spark, sf).groupingSets([["p"], ["q"]], "p", "q").agg(F.sum("xi").alias("xi")).select("p", "q", "xi"), f"{_BS} SELECT p, q, sum(xi)::BIGINT AS xi FROM b GROUP BY GROUPING SETS ((p), (q))")
add("agg_pivot_modes", lambda spark, sf: modes(spark, sf, "copart_thin").groupBy("p").pivot("mode", ["dense", "sparse"]).agg(F.sum("xi")), f"WITH {modes_sql('copart_thin')} SELECT p, (sum(xi) FILTER (WHERE mode = 'dense'))::BIGINT AS dense, (sum(xi) FILTER (WHERE mode = 'sparse'))::BIGINT AS sparse FROM mm GROUP BY p")
add("agg_bitor", lambda spark, sf: E("usage")(spark, sf).groupBy("src").agg(F.bit_or(F.col("dst") % 1024).alias("bits")), f"{_E['usage']} SELECT src, bit_or(dst % 1024)::BIGINT AS bits FROM e GROUP BY src")
add("agg_maxby", lambda spark, sf: table(spark, sf, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("best"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("worst")), "SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS best, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS worst FROM orders GROUP BY 1")
add("agg_percentile", lambda spark, sf: table(spark, sf, "orders").groupBy("o_orderstatus").agg(F.round(F.expr("percentile(o_totalprice, 0.5)"), 4).alias("median"), F.round(F.expr("percentile(o_totalprice, 0.9)"), 4).alias("p90")), "SELECT o_orderstatus, round(quantile_cont(o_totalprice, 0.5), 4) AS median, round(quantile_cont(o_totalprice, 0.9), 4) AS p90 FROM orders GROUP BY 1")
add("agg_collect", lambda spark, sf: E("copart_thin")(spark, sf).groupBy("src").agg(F.array_join(F.transform(F.sort_array(F.collect_list("dst")), lambda x: x.cast("string")), ",").alias("to")), f"{_E['copart_thin']} SELECT src, string_agg(dst::VARCHAR, ',' ORDER BY dst) AS to FROM e GROUP BY src")
add("agg_approx_distinct", lambda spark, sf: table(spark, sf, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users")))
add("agg_hll", lambda spark, sf: table(spark, sf, "events").groupBy("event_type").agg(F.hll_sketch_agg("user_id").alias("s")).agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("users")))
add("agg_theta", lambda spark, sf: table(spark, sf, "events").groupBy("event_type").agg(F.expr("theta_sketch_estimate(theta_sketch_agg(user_id))").alias("users")))



@key("agg_sketch_errors", "SELECT unnest(['approx', 'hll', 'theta']) AS sketch, true AS within_5_percent")
def agg_sketch_errors(spark, sf):
    """Distinct users by sketches against the exact number."""
    e = table(spark, sf, "events")
    one = e.agg(F.countDistinct("user_id").alias("n"), F.approx_count_distinct("user_id", 0.01).alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id", 14)).alias("hll"), F.expr("theta_sketch_estimate(theta_sketch_agg(user_id))").alias("theta"))
    far = one.unpivot(["n"], ["approx", "hll", "theta"], "sketch", "users")
    return far.select("sketch", (F.abs(F.col("users") / F.col("n") - 1) < 0.05).alias("within_5_percent"))


# --- windows ----------------------------------------------------------------------------------------------------------
@key("win_rank_pagerank", pagerank_sql("purchase", 2, out="SELECT id, rank() OVER (ORDER BY r DESC) AS rk, dense_rank() OVER (ORDER BY r DESC) AS dr, row_number() OVER (ORDER BY r DESC, id) AS rn FROM (SELECT id, round(rank + 1e-9, 6) AS r FROM r{n}) ORDER BY rn LIMIT 100"))
def win_rank(spark, sf):
    """The 100 best: ranked after a distributed top-k that keeps ties of the last one."""
    v = cut(alg.pagerank(graph(spark, sf, "purchase"), 2, beta=16).values.select("id", F.round(F.col("rank") + 1e-9, 6).alias("r")), "ranks")
    top = v.orderBy(F.desc("r"), "id").limit(100)
    by = Window.orderBy(F.desc("r"))
    return top.select("id", F.rank().over(by).cast("long").alias("rk"), F.dense_rank().over(by).cast("long").alias("dr"), F.row_number().over(Window.orderBy(F.desc("r"), "id")).cast("long").alias("rn"))


_C = lambda: Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")
_CW = "OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)"
add("win_ntile", lambda spark, sf: table(spark, sf, "customer").select("c_custkey", F.ntile(4).over(_C()).cast("long").alias("quarter")), f"SELECT c_custkey, ntile(4) {_CW} AS quarter FROM customer")
add("win_dist", lambda spark, sf: table(spark, sf, "customer").select("c_custkey", F.round(F.percent_rank().over(_C()), 9).alias("pr"), F.round(F.cume_dist().over(_C()), 9).alias("cd")), f"SELECT c_custkey, round(percent_rank() {_CW}, 9) AS pr, round(cume_dist() {_CW}, 9) AS cd FROM customer")
_U = lambda: Window.partitionBy("user_id").orderBy("ts", "event_id")
_UW = "PARTITION BY user_id ORDER BY ts, event_id"
add("win_lead_transitions", lambda spark, sf: table(spark, sf, "events").select("event_id", F.lead("event_type").over(_U()).alias("next"), F.lag("event_type").over(_U()).alias("prev")), f"SELECT event_id, lead(event_type) OVER ({_UW}) AS next, lag(event_type) OVER ({_UW}) AS prev FROM events")
add("win_running_mass", lambda spark, sf: _B(spark, sf).select("p", "q", F.sum("xi").over(Window.partitionBy("p").orderBy("q")).alias("mass")), f"{_BS} SELECT p, q, (sum(xi) OVER (PARTITION BY p ORDER BY q))::BIGINT AS mass FROM b")
add("win_rows_frame", lambda spark, sf: table(spark, sf, "events").select("event_id", F.round(F.avg("value").over(_U().rowsBetween(-2, 0)), 6).alias("mean3")), f"SELECT event_id, round(avg(value) OVER ({_UW} ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS mean3 FROM events")
add("win_range_frame", lambda spark, sf: table(spark, sf, "orders").withColumn("d", F.unix_date(F.col("o_orderdate").cast("date"))).select("o_orderkey", N().over(Window.partitionBy("o_custkey").orderBy("d").rangeBetween(-30, 0)).alias("in30")), "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY (o_orderdate::DATE - DATE '1970-01-01') RANGE BETWEEN 30 PRECEDING AND CURRENT ROW) AS in30 FROM orders")
add("win_first_last", lambda spark, sf: table(spark, sf, "events").select("event_id", F.first("event_type").over(_U().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("first"), F.last("event_type").over(_U().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("last"), F.nth_value("event_type", 2).over(_U().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("second")), f"SELECT event_id, first_value(event_type) OVER w AS first, last_value(event_type) OVER w AS last, nth_value(event_type, 2) OVER w AS second FROM events WINDOW w AS ({_UW} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")

# --- sorts and limits -------------------------------------------------------------------------------------------------
add("topk_degree", lambda spark, sf: E("hetero")(spark, sf).groupBy("dst").agg(N().alias("c")).orderBy(F.desc("c"), "dst").limit(20), f"{_E['hetero']} SELECT dst, count(*)::BIGINT AS c FROM e GROUP BY dst ORDER BY c DESC, dst LIMIT 20")
add("topk_per_nation", lambda spark, sf: table(spark, sf, "customer").withColumn("r", F.row_number().over(Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey"))).where("r <= 3").select("c_nationkey", "c_custkey", F.col("r").cast("long").alias("r")), "SELECT c_nationkey, c_custkey, r FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) WHERE r <= 3")
add("sort_global", lambda spark, sf: table(spark, sf, "supplier").select("s_suppkey", "s_acctbal").orderBy("s_acctbal", "s_suppkey"), "SELECT s_suppkey, s_acctbal FROM supplier ORDER BY 2, 1")
add("limit_offset", lambda spark, sf: table(spark, sf, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(10).limit(15), "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 15 OFFSET 10")

# --- sets -------------------------------------------------------------------------------------------------------------
_F = lambda spark, sf: graph(spark, sf, "copart_thin").edges.select("src", "dst")
_R = lambda spark, sf: graph(spark, sf, "copart_thin").edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
_P = lambda spark, sf: table(spark, sf, "lineitem").select("l_suppkey", (F.col("l_partkey") % 50).alias("k"))
_PS = "SELECT l_suppkey, l_partkey % 50 AS k FROM lineitem"
add("set_unionall", lambda spark, sf: _F(spark, sf).unionAll(_R(spark, sf)).groupBy("src").agg(N().alias("c")), f"{_E['copart_thin']} SELECT src, count(*)::BIGINT AS c FROM (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e) GROUP BY src")
add("set_symmetrise", lambda spark, sf: graph(spark, sf, "copart_thin").symmetric().edges.select("src", "dst"), f"WITH {edges_cte('copart_thin', True)} SELECT src, dst FROM e")
add("set_intersect", lambda spark, sf: _F(spark, sf).intersect(_R(spark, sf)), f"{_E['copart_thin']} SELECT src, dst FROM e INTERSECT SELECT dst, src FROM e")
add("set_except", lambda spark, sf: _F(spark, sf).subtract(_R(spark, sf)), f"{_E['copart_thin']} SELECT src, dst FROM e EXCEPT SELECT dst, src FROM e")
add("set_intersect_all", lambda spark, sf: _P(spark, sf).where("l_suppkey % 2 = 0").select("k").intersectAll(_P(spark, sf).where("l_suppkey % 3 = 0").select("k")), f"SELECT k FROM ({_PS}) WHERE l_suppkey % 2 = 0 INTERSECT ALL SELECT k FROM ({_PS}) WHERE l_suppkey % 3 = 0")
add("set_except_all", lambda spark, sf: _P(spark, sf).where("l_suppkey % 2 = 0").select("k").exceptAll(_P(spark, sf).where("l_suppkey % 3 = 0").select("k")), f"SELECT k FROM ({_PS}) WHERE l_suppkey % 2 = 0 EXCEPT ALL SELECT k FROM ({_PS}) WHERE l_suppkey % 3 = 0")

# --- filters ----------------------------------------------------------------------------------------------------------

add("edges_filtered", lambda spark, sf: E("supply")(spark, sf).where(F.col("w").between(40, 60)).select("src", "dst", "w"), f"{_E['supply']} SELECT src, dst, w FROM e WHERE w BETWEEN 40 AND 60")


@key("subgraph_segment", f"{_E['purchase']} SELECT src, dst FROM e WHERE src IN (SELECT c_custkey FROM customer WHERE c_mktsegment LIKE 'B%')")
def subgraph_segment(spark, sf):
    keep = table(spark, sf, "customer").where(F.col("c_mktsegment").like("B%")).select(F.col("c_custkey").alias("src"))
    return E("purchase")(spark, sf).join(keep, "src", "left_semi").select("src", "dst")


add("no_selfloops", lambda spark, sf: graph(spark, sf, "transitions").edges.where("src <> dst"), f"WITH {edges_cte('transitions')} SELECT src, dst, w FROM e WHERE src <> dst")
add("edge_weights", lambda spark, sf: E("copart")(spark, sf).groupBy("w").agg(N().alias("edges")), f"{_E['copart']} SELECT w, count(*)::BIGINT AS edges FROM e GROUP BY w")

# --- functions --------------------------------------------------------------------------------------------------------
add("fn_href", lambda spark, sf: table(spark, sf, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)'), 1)).alias("href")).groupBy("href").agg(N().alias("c")), """SELECT href, count(*)::BIGINT AS c FROM (SELECT unnest(regexp_extract_all(html, 'href="([^"]+)', 1)) AS href FROM pages) GROUP BY 1""")
add("fn_host", lambda spark, sf: table(spark, sf, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/:?#]+)", 1).alias("host")), "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host FROM pages")
add("fn_md5_groups", lambda spark, sf: table(spark, sf, "documents").groupBy(F.md5(F.col("text").cast("binary")).alias("m")).agg(N().alias("c")).where("c > 1"), "SELECT md5(text) AS m, count(*)::BIGINT AS c FROM documents GROUP BY 1 HAVING count(*) > 1")
add("fn_text_case", lambda spark, sf: table(spark, sf, "customer").select("c_custkey", F.lower("c_mktsegment").alias("low"), F.substring("c_name", 1, 8).alias("head"), F.length("c_name").alias("len"), F.concat_ws("-", "c_mktsegment", F.col("c_nationkey").cast("string")).alias("tag"), F.translate("c_mktsegment", "AEIOU", "aeiou").alias("tr")), "SELECT c_custkey, lower(c_mktsegment) AS low, substr(c_name, 1, 8) AS head, length(c_name)::INT AS len, c_mktsegment || '-' || c_nationkey AS tag, translate(c_mktsegment, 'AEIOU', 'aeiou') AS tr FROM customer")
add("fn_edges_by_month", lambda spark, sf: table(spark, sf, "lineitem").groupBy(F.date_format(F.trunc(F.col("l_shipdate").cast("date"), "month"), "yyyy-MM-dd").alias("month")).agg(N().alias("lines")), "SELECT strftime(date_trunc('month', l_shipdate), '%Y-%m-%d') AS month, count(*)::BIGINT AS lines FROM lineitem GROUP BY 1")
add("fn_datediff", lambda spark, sf: table(spark, sf, "lineitem").join(table(spark, sf, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy(F.datediff(F.col("l_shipdate").cast("date"), F.col("o_orderdate").cast("date")).alias("days")).agg(N().alias("c")), "SELECT date_diff('day', o_orderdate::DATE, l_shipdate::DATE)::INT AS days, count(*)::BIGINT AS c FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
add("fn_date_parts", lambda spark, sf: table(spark, sf, "orders").groupBy(F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q")).agg(N().alias("c")), "SELECT year(o_orderdate)::INT AS y, quarter(o_orderdate)::INT AS q, count(*)::BIGINT AS c FROM orders GROUP BY 1, 2")
add("fn_cost_arith", lambda spark, sf: _B(spark, sf).select("p", "q", F.round(F.log2("xi"), 9).alias("lg"), F.expr("xi div 3").alias("third"), F.greatest("p", "q").alias("hi"), F.least("p", "q").alias("lo"), F.pmod(F.col("p") - F.col("q"), F.lit(8)).alias("diag")), f"{_BS} SELECT p, q, round(log2(xi), 9) AS lg, xi // 3 AS third, greatest(p, q) AS hi, least(p, q) AS lo, ((p - q) % 8 + 8) % 8 AS diag FROM b")
add("fn_math", lambda spark, sf: table(spark, sf, "supplier").select("s_suppkey", F.round(F.sqrt(F.abs("s_acctbal")), 6).alias("root"), F.ceil("s_acctbal").alias("up"), F.floor("s_acctbal").alias("down"), F.round(F.pow(F.abs("s_acctbal"), F.lit(0.3)), 6).alias("pw"), F.signum("s_acctbal").alias("sg")), "SELECT s_suppkey, round(sqrt(abs(s_acctbal)), 6) AS root, ceil(s_acctbal)::BIGINT AS up, floor(s_acctbal)::BIGINT AS down, round(pow(abs(s_acctbal), 0.3::DOUBLE), 6) AS pw, sign(s_acctbal)::DOUBLE AS sg FROM supplier")
add("fn_try_divide", lambda spark, sf: table(spark, sf, "part").select("p_partkey", F.round(F.try_divide(F.col("p_retailprice"), F.col("p_size") % 3), 6).alias("x"), F.try_to_number(F.lit("12x"), F.lit("999")).isNull().alias("bad")), "SELECT p_partkey, CASE WHEN p_size % 3 = 0 THEN NULL ELSE round(p_retailprice / (p_size % 3), 6) END AS x, true AS bad FROM part")
_NEAR = f"{_E['copart_thin']}, a AS (SELECT src, list(dst ORDER BY dst) AS l FROM e GROUP BY src)"


def _arrays(spark, sf):
    return E("copart_thin")(spark, sf).groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("l"))


add("fn_array_neighbors", lambda spark, sf: _arrays(spark, sf).select("src", F.posexplode("l").alias("pos", "dst")), f"{_NEAR} SELECT src, (u.pos - 1)::INT AS pos, l[u.pos] AS dst FROM a, LATERAL (SELECT unnest(range(1, len(l) + 1)) AS pos) u")
add("fn_array_hof", lambda spark, sf: _arrays(spark, sf).select("src", F.aggregate("l", F.lit(0).cast("long"), lambda s, x: s + x * 2).alias("twice"), F.size(F.filter("l", lambda x: x % 2 == 0)).alias("even"), F.exists("l", lambda x: x > 100).alias("big"), F.array_max(F.transform("l", lambda x: x % 97)).alias("top")), f"{_NEAR} SELECT src, list_sum(list_transform(l, lambda x: x * 2))::BIGINT AS twice, len(list_filter(l, lambda x: x % 2 = 0))::INT AS even, len(list_filter(l, lambda x: x > 100)) > 0 AS big, list_max(list_transform(l, lambda x: x % 97)) AS top FROM a")
add("fn_cosine_knn", lambda spark, sf: (lambda e: vectors.nearest(e, e, 10).select("src", "dst", F.col("cosine").alias("w")))(table(spark, sf, "embeddings")), f"WITH {edges_cte('knn')} SELECT src, dst, w FROM e")
add("fn_map_labels", lambda spark, sf: table(spark, sf, "events").groupBy("user_id", "event_type").agg(N().alias("c")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "c"))).alias("m")).select("user_id", F.coalesce(F.col("m")["view"], F.lit(0)).alias("views"), F.size("m").alias("kinds"), F.size(F.map_filter("m", lambda k, v: v > 10)).alias("often")), f"SELECT user_id, coalesce(sum(c) FILTER (WHERE event_type = 'view'), 0)::BIGINT AS views, count(*)::INT AS kinds, (count(*) FILTER (WHERE c > 10))::INT AS often FROM ({_TYPES.replace('event_type, count', 'user_id, event_type, count').replace('GROUP BY 1', 'GROUP BY 1, 2')}) GROUP BY 1")
add("fn_struct", lambda spark, sf: table(spark, sf, "nation").select(F.struct("n_nationkey", F.struct("n_name", "n_regionkey").alias("in")).alias("s")).select(F.col("s.n_nationkey").alias("k"), F.col("s.in.n_name").alias("name")), "SELECT n_nationkey AS k, n_name AS name FROM nation")
add("fn_json_usage", lambda spark, sf: table(spark, sf, "events").groupBy(F.from_json("props", "k int")["k"].alias("k")).agg(N().alias("c")), "SELECT json_extract_string(props, '$.k')::INT AS k, count(*)::BIGINT AS c FROM events GROUP BY 1")
add("fn_json_roundtrip", lambda spark, sf: table(spark, sf, "nation").select("n_nationkey", F.to_json(F.struct("n_name", "n_regionkey")).alias("j")).select("n_nationkey", F.variant_get(F.parse_json("j"), "$.n_name", "string").alias("name"), F.get_json_object("j", "$.n_regionkey").cast("int").alias("r")), "SELECT n_nationkey, n_name AS name, n_regionkey AS r FROM nation")


# --- SQL --------------------------------------------------------------------------------------------------------------
@key("sql_blocks_view", f"{_BS} SELECT p, sum(xi)::BIGINT AS edges FROM b WHERE q >= 4 GROUP BY p")
def sql_blocks_view(spark, sf):
    _B(spark, sf).createOrReplaceTempView("blocks")
    return spark.sql("SELECT p, sum(xi) AS edges FROM blocks WHERE q >= 4 GROUP BY p")


@key("sql_recursive_bfs", f"WITH RECURSIVE {edges_cte('turns')}, r(id, dist) AS (SELECT id, 0 FROM v WHERE id = 0 UNION ALL SELECT e.dst, r.dist + 1 FROM r JOIN e ON e.src = r.id) SELECT id, min(dist)::INT AS dist FROM r GROUP BY id")
def sql_recursive_bfs(spark, sf):
    graph(spark, sf, "turns").edges.createOrReplaceTempView("edges")
    return spark.sql("WITH RECURSIVE r(id, dist) AS (SELECT 0L, 0 UNION ALL SELECT e.dst, r.dist + 1 FROM r JOIN edges e ON e.src = r.id) SELECT id, min(dist) AS dist FROM r GROUP BY id")


@key("sql_params", f"{_BS} SELECT p, q, xi FROM b WHERE xi >= 3 AND p = 2")
def sql_params(spark, sf):
    return spark.sql("SELECT p, q, xi FROM {b} WHERE xi >= :least AND p = :p", args={"least": 3, "p": 2}, b=_B(spark, sf))
