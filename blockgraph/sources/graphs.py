"""The given tables as graphs: edges(src, dst[, w]) over vertex ids 0 .. n - 1, and the same edges as DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from blockgraph.storage import cut, table


@dataclass(frozen=True)
class Graph:
    """edges: src, dst (bigint) and, where ``weighted``, w (double). half: of a graph of ``mutual``, the edges with src < dst."""

    name: str
    n: int
    edges: DataFrame
    weighted: bool = False
    meta: dict = field(default_factory=dict)
    half: DataFrame | None = None

    @property
    def vertices(self) -> DataFrame:
        return self.edges.sparkSession.range(self.n).select("id")

    def symmetric(self) -> "Graph":
        """Both directions of every edge, once."""
        if self.half is not None:
            return mutual(f"{self.name}_both", self.n, self.half, self.weighted)
        back = self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *(["w"] if self.weighted else []))
        both = self.edges.select(*back.columns).union(back)
        both = both.groupBy("src", "dst").agg(F.max("w").alias("w")) if self.weighted else both.distinct()
        return Graph(f"{self.name}_both", self.n, both, self.weighted)


def mutual(name: str, n: int, half: DataFrame, weighted: bool = False, meta: dict | None = None) -> Graph:
    """The graph of the edges of ``half`` (src < dst, each once) in both directions."""
    back = half.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *(["w"] if weighted else []))
    return Graph(name, n, half.select(*back.columns).union(back), weighted, meta or {}, half)


def _count(spark: SparkSession, sf: str, name: str) -> int:
    return table(spark, sf, name).count()


def dense_ids(df: DataFrame, order: list[str], name: str = "id") -> DataFrame:
    """df with ids 0 .. rows - 1 in the order of its columns: rows are range-partitioned, counted by partition and numbered inside.

    The ranges are written before they are counted: planned a second time, their sampled bounds and merged partitions can differ."""
    ranged = cut(df.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()), "ranged")
    inside = Window.partitionBy("_part").orderBy(*order)
    sizes = ranged.groupBy("_part").count()
    offsets = sizes.withColumn("_from", F.coalesce(F.sum("count").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("count")
    numbered = ranged.withColumn("_n", F.row_number().over(inside) - 1).join(F.broadcast(offsets), "_part")  # one row per partition
    return numbered.withColumn(name, (F.col("_from") + F.col("_n")).cast("long")).drop("_part", "_n", "_from")


def supply(spark: SparkSession, sf: str) -> Graph:
    s = _count(spark, sf, "supplier")
    e = table(spark, sf, "lineitem").groupBy(F.col("l_suppkey").alias("src"), (F.col("l_partkey") + s).alias("dst")).agg(F.sum("l_quantity").alias("w"))
    return Graph("supply", s + _count(spark, sf, "part"), e, True)


def copart(spark: SparkSession, sf: str) -> Graph:
    """Lines are dealt by order once, for both sides of the join; a pair of parts is counted in one direction."""
    once = table(spark, sf, "lineitem").select("l_orderkey", "l_partkey").repartition("l_orderkey").distinct()
    a, b = once.withColumnRenamed("l_partkey", "src"), once.withColumnRenamed("l_partkey", "dst")
    half = a.join(b, "l_orderkey").where("src < dst").groupBy("src", "dst").agg(F.count(F.lit(1)).cast("double").alias("w"))
    return mutual("copart", _count(spark, sf, "part"), half, True)


def copart_thin(spark: SparkSession, sf: str) -> Graph:
    line = table(spark, sf, "lineitem")
    a = line.where("l_linenumber = 1 and l_quantity >= 45").select("l_orderkey", F.col("l_partkey").alias("src"))
    e = a.join(line.select("l_orderkey", F.col("l_partkey").alias("dst")), "l_orderkey").where("src <> dst").select("src", "dst").distinct()
    return Graph("copart_thin", _count(spark, sf, "part"), e)


def hetero(spark: SparkSession, sf: str) -> Graph:
    sizes = {t: _count(spark, sf, t) for t in ("region", "nation", "customer", "supplier", "part", "orders")}
    at, off = 0, {}
    for t, n in sizes.items():
        off[t], at = at, at + n
    c, s, o, line = (table(spark, sf, t) for t in ("customer", "supplier", "orders", "lineitem"))
    edge = lambda df, a, ta, b, tb: df.select((F.col(a) + off[ta]).cast("long").alias("src"), (F.col(b) + off[tb]).cast("long").alias("dst"))
    e = edge(table(spark, sf, "nation"), "n_nationkey", "nation", "n_regionkey", "region")
    for part in (
        edge(c, "c_custkey", "customer", "c_nationkey", "nation"), edge(s, "s_suppkey", "supplier", "s_nationkey", "nation"), edge(o, "o_orderkey", "orders", "o_custkey", "customer"),
        edge(line, "l_orderkey", "orders", "l_partkey", "part"), edge(line, "l_partkey", "part", "l_suppkey", "supplier"),
    ):
        e = e.union(part)
    return Graph("hetero", at, e.distinct(), meta=off)


def purchase(spark: SparkSession, sf: str) -> Graph:
    c = _count(spark, sf, "customer")
    e = table(spark, sf, "orders").join(table(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).select(F.col("o_custkey").alias("src"), (F.col("l_partkey") + c).alias("dst")).distinct()
    return Graph("purchase", c + _count(spark, sf, "part"), e)


def placed(spark: SparkSession, sf: str) -> Graph:
    c = _count(spark, sf, "customer")
    e = table(spark, sf, "orders").select(F.col("o_custkey").alias("src"), (F.col("o_orderkey") + c).alias("dst"))
    return Graph("placed", c + _count(spark, sf, "orders"), e)


def usage(spark: SparkSession, sf: str) -> Graph:
    ev = table(spark, sf, "events").select("user_id", F.get_json_object("props", "$.k").cast("long").alias("k"))
    u, k = ev.agg(F.max("user_id"), F.max("k")).first()
    return Graph("usage", u + 1 + k + 1, ev.select(F.col("user_id").alias("src"), (F.col("k") + u + 1).alias("dst")).distinct())


def weblinks(spark: SparkSession, sf: str) -> Graph:
    pages = table(spark, sf, "pages")
    raw = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)'), 1)).alias("href")).distinct()
    n = pages.count()
    targets = dense_ids(raw.select("href").distinct(), ["href"])
    e = raw.join(targets, "href").select(F.col("page_id").alias("src"), (F.col("id") + n).alias("dst"))
    return Graph("weblinks", n + targets.count(), e)


def transitions(spark: SparkSession, sf: str) -> Graph:
    ev = table(spark, sf, "events").select("user_id", "ts", "event_id", "event_type")
    after = ev.withColumn("next", F.lead("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id")))
    kinds = dense_ids(ev.select("event_type").distinct(), ["event_type"])
    e = after.where("next is not null").groupBy("event_type", "next").count()
    e = e.join(F.broadcast(kinds), "event_type").withColumnRenamed("id", "src").join(F.broadcast(kinds.select(F.col("event_type").alias("next"), F.col("id").alias("dst"))), "next")
    return Graph("transitions", kinds.count(), e.select("src", "dst", F.col("count").cast("double").alias("w")), True)


def turns(spark: SparkSession, sf: str) -> Graph:
    t = dense_ids(table(spark, sf, "conversations").select("conv_id", "turn"), ["conv_id", "turn"])
    e = t.withColumn("dst", F.lead("id").over(Window.partitionBy("conv_id").orderBy("turn"))).where("dst is not null")
    return Graph("turns", t.count(), e.select(F.col("id").alias("src"), "dst"))


def dupdocs(spark: SparkSession, sf: str) -> Graph:
    docs = table(spark, sf, "documents").select("doc_id", F.md5(F.col("text").cast("binary")).alias("m"))
    first = docs.groupBy("m").agg(F.min("doc_id").alias("low"), F.count(F.lit(1)).alias("k")).where("k > 1")
    return Graph("dupdocs", docs.count(), docs.join(first, "m").where("doc_id <> low").select(F.col("doc_id").alias("src"), F.col("low").alias("dst")))


def knn(spark: SparkSession, sf: str, k: int = 10) -> Graph:
    """k nearest by cosine. The table is compared in blocks of vectors: each block is a bounded broadcast matrix."""
    from blockgraph.functions.vectors import nearest

    e = table(spark, sf, "embeddings")
    return Graph("knn", e.count(), nearest(e, e, k).select("src", "dst", F.col("cosine").alias("w")), True)


def rmat(spark: SparkSession, scale: int, k: int, seed: int = 7, parts: tuple[float, float, float] = (0.57, 0.19, 0.19)) -> Graph:
    """Recursive-matrix graph: each level's quadrant from a digit of md5(seed, edge, level), so that SQL gives the same edges."""
    a, b, c = (round(x * 65536) for x in (parts[0], parts[0] + parts[1], sum(parts)))
    e = spark.range(k * 2**scale)
    src = dst = F.lit(0).cast("long")
    for level in range(scale):
        d = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("id").cast("string"), F.lit(str(level)))), 1, 4), 16, 10).cast("int")
        src = src * 2 + F.when(d >= b, 1).otherwise(0)
        dst = dst * 2 + F.when(((d >= a) & (d < b)) | (d >= c), 1).otherwise(0)
    return Graph(f"rmat_{scale}_{k}", 2**scale, e.select(src.alias("src"), dst.alias("dst")).distinct())


def rmat_sql(scale: int, k: int, seed: int = 7, parts: tuple[float, float, float] = (0.57, 0.19, 0.19)) -> str:
    a, b, c = (round(x * 65536) for x in (parts[0], parts[0] + parts[1], sum(parts)))
    digits = ", ".join(f"('0x' || substr(md5('{seed}:' || i || ':{v}'), 1, 4))::INT AS d{v}" for v in range(scale))
    src = " + ".join(f"(CASE WHEN d{v} >= {b} THEN {2 ** (scale - 1 - v)} ELSE 0 END)" for v in range(scale))
    dst = " + ".join(f"(CASE WHEN (d{v} >= {a} AND d{v} < {b}) OR d{v} >= {c} THEN {2 ** (scale - 1 - v)} ELSE 0 END)" for v in range(scale))
    return f"SELECT DISTINCT ({src})::BIGINT AS src, ({dst})::BIGINT AS dst FROM (SELECT {digits} FROM range({k * 2**scale}) t(i))"


_N = {t: f"(SELECT count(*) FROM {t})" for t in ("region", "nation", "customer", "supplier", "part", "orders", "pages", "documents", "embeddings", "conversations")}
_OFF = {"region": "0", "nation": _N["region"]}
for _a, _b in zip(("nation", "customer", "supplier", "part"), ("customer", "supplier", "part", "orders"), strict=True):
    _OFF[_b] = f"{_OFF[_a]} + {_N[_a]}"
_LEAD = "lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id)"
_ONCE = "(SELECT DISTINCT l_orderkey, l_partkey FROM lineitem)"

#: DuckDB SQL of each graph's edges.
EDGES_SQL: dict[str, str] = {
    "supply": f"SELECT l_suppkey AS src, l_partkey + {_N['supplier']} AS dst, sum(l_quantity) AS w FROM lineitem GROUP BY 1, 2",
    "copart": f"SELECT a.l_partkey AS src, b.l_partkey AS dst, count(*)::DOUBLE AS w FROM {_ONCE} a JOIN {_ONCE} b USING (l_orderkey) WHERE a.l_partkey <> b.l_partkey GROUP BY 1, 2",
    "copart_thin": "SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst FROM lineitem a JOIN lineitem b USING (l_orderkey) WHERE a.l_linenumber = 1 AND a.l_quantity >= 45 AND a.l_partkey <> b.l_partkey",
    "hetero": f"""SELECT DISTINCT src::BIGINT AS src, dst::BIGINT AS dst FROM (
        SELECT n_nationkey + {_OFF["nation"]} AS src, n_regionkey + {_OFF["region"]} AS dst FROM nation
        UNION ALL SELECT c_custkey + {_OFF["customer"]}, c_nationkey + {_OFF["nation"]} FROM customer UNION ALL SELECT s_suppkey + {_OFF["supplier"]}, s_nationkey + {_OFF["nation"]} FROM supplier
        UNION ALL SELECT o_orderkey + {_OFF["orders"]}, o_custkey + {_OFF["customer"]} FROM orders UNION ALL SELECT l_orderkey + {_OFF["orders"]}, l_partkey + {_OFF["part"]} FROM lineitem
        UNION ALL SELECT l_partkey + {_OFF["part"]}, l_suppkey + {_OFF["supplier"]} FROM lineitem)""",
    "purchase": f"SELECT DISTINCT o_custkey AS src, l_partkey + {_N['customer']} AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "placed": f"SELECT o_custkey AS src, o_orderkey + {_N['customer']} AS dst FROM orders",
    "usage": "SELECT DISTINCT user_id AS src, json_extract_string(props, '$.k')::BIGINT + (SELECT max(user_id) + 1 FROM events) AS dst FROM events",
    "weblinks": f"""SELECT page_id AS src, t.id + {_N["pages"]} AS dst FROM (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]+)', 1)) AS href FROM pages) r
        JOIN (SELECT href, row_number() OVER (ORDER BY href) - 1 AS id FROM (SELECT DISTINCT unnest(regexp_extract_all(html, 'href="([^"]+)', 1)) AS href FROM pages)) t USING (href)""",
    "transitions": f"""SELECT a.id AS src, b.id AS dst, count(*)::DOUBLE AS w FROM (SELECT event_type, {_LEAD} AS nxt FROM events) e
        JOIN (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS id FROM (SELECT DISTINCT event_type FROM events)) a ON e.event_type = a.event_type
        JOIN (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS id FROM (SELECT DISTINCT event_type FROM events)) b ON e.nxt = b.event_type GROUP BY 1, 2""",
    "turns": "SELECT id AS src, nxt AS dst FROM (SELECT id, lead(id) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM (SELECT conv_id, turn, row_number() OVER (ORDER BY conv_id, turn) - 1 AS id FROM conversations)) WHERE nxt IS NOT NULL",
    "dupdocs": "SELECT doc_id AS src, low AS dst FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY md5(text)) AS low FROM documents) WHERE doc_id <> low",
    "knn": """SELECT src, dst, w FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) AS rk FROM (SELECT a.vec_id AS src, b.vec_id AS dst,
        round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) / sqrt(list_dot_product(a.embedding::DOUBLE[], a.embedding::DOUBLE[]) * list_dot_product(b.embedding::DOUBLE[], b.embedding::DOUBLE[])), 9) AS w
        FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id)) WHERE rk <= 10""",
    "rmat": rmat_sql(10, 3),
    "rmat_12": rmat_sql(12, 3),
}
#: DuckDB SQL of each graph's number of vertices.
N_SQL: dict[str, str] = {
    "supply": f"{_N['supplier']} + {_N['part']}", "copart": _N["part"], "copart_thin": _N["part"], "hetero": f"{_OFF['orders']} + {_N['orders']}", "purchase": f"{_N['customer']} + {_N['part']}",
    "placed": f"{_N['customer']} + {_N['orders']}", "usage": "(SELECT max(user_id) + 1 + max(json_extract_string(props, '$.k')::BIGINT) + 1 FROM events)",
    "weblinks": f"""{_N["pages"]} + (SELECT count(DISTINCT href) FROM (SELECT unnest(regexp_extract_all(html, 'href="([^"]+)', 1)) AS href FROM pages))""",
    "transitions": "(SELECT count(DISTINCT event_type) FROM events)", "turns": _N["conversations"], "dupdocs": _N["documents"], "knn": _N["embeddings"], "rmat": str(2**10), "rmat_12": str(2**12),
}

GRAPHS: dict[str, Callable[[SparkSession, str], Graph]] = {f.__name__: f for f in (supply, copart, copart_thin, hetero, purchase, placed, usage, weblinks, transitions, turns, dupdocs, knn)}
GRAPHS["rmat"] = lambda spark, sf: rmat(spark, 10, 3)
GRAPHS["rmat_12"] = lambda spark, sf: rmat(spark, 12, 3)


def edges_cte(name: str, symmetric: bool = False) -> str:
    """WITH-list of e(src, dst[, w]) and nv(n) of a graph, without the word WITH."""
    e = f"e0 AS MATERIALIZED ({EDGES_SQL[name]})"
    e += ", e AS MATERIALIZED (SELECT src, dst FROM e0 UNION SELECT dst, src FROM e0)" if symmetric else ", e AS (SELECT * FROM e0)"
    return f"{e}, nv AS (SELECT ({N_SQL[name]})::BIGINT AS n), v AS (SELECT unnest(range((SELECT n FROM nv)))::BIGINT AS id)"
