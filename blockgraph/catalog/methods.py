"""Layout, cost, path, algorithm, baseline and workload keys."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from blockgraph.operators import algorithms as alg
from blockgraph.operators import baselines, lanczos, vectorops as vo
from blockgraph.plans import costmodel as cm
from blockgraph.plans import engine, layout as lay, metrics, schemes, simulate
from blockgraph.registry import add, key
from blockgraph.sources.graphs import GRAPHS, edges_cte, mutual
from blockgraph.storage import cut, settings, table

BETA = {"hetero": 128, "copart_thin": 16, "placed": 64, "weblinks": 64, "supply": 16, "copart": 16, "purchase": 16, "rmat": 32, "turns": 8, "dupdocs": 8, "transitions": 1, "usage": 8, "knn": 8}
_graphs: dict = {}


def graph(spark: SparkSession, sf: str, name: str):
    """A graph with its edges written once for a session and folder."""
    at = (spark.sparkContext.applicationId, sf, name)
    if at not in _graphs:
        g = GRAPHS[name](spark, sf)
        if g.half is None:
            _graphs[at] = type(g)(g.name, g.n, cut(g.edges, f"graph-{name}"), g.weighted, g.meta)
        else:
            _graphs[at] = mutual(g.name, g.n, cut(g.half, f"graph-{name}", compression="zstd"), g.weighted, g.meta)
    return _graphs[at]


def blocks_sql(name: str, beta: int | None = None, more: str = "") -> str:
    """WITH-list up to b(p, q, xi)."""
    beta = beta or BETA[name]
    return f"{edges_cte(name)}, k AS (SELECT greatest(1, (n + {beta - 1}) // {beta}) AS width FROM nv), g AS (SELECT src, dst, (src // width)::INT AS p, (dst // width)::INT AS q FROM e, k), b AS (SELECT p, q, count(*)::BIGINT AS xi{more} FROM g GROUP BY p, q)"


def modes_sql(name: str, beta: int | None = None) -> str:
    beta = beta or BETA[name]
    return blocks_sql(name, beta) + f", m AS (SELECT p, q, xi, 1.0::DOUBLE / {beta} + (2 * xi / width::DOUBLE) * 3.0::DOUBLE AS crit FROM b, k), mm AS (SELECT *, CASE WHEN crit < 1 THEN 'sparse' ELSE 'dense' END AS mode FROM m)"


def modes(spark: SparkSession, sf: str, name: str, beta: int | None = None) -> DataFrame:
    g, beta = graph(spark, sf, name), beta or BETA[name]
    return cm.classify(lay.block_stats(lay.blocked(g.edges, g.n, beta)), beta, lay.width_of(g.n, beta))


SIZED = ("placed", "supply", "usage")


def sizes(spark: SparkSession, sf: str) -> DataFrame:
    """graph, v, e of graphs of the given tables: vertices that have an edge, and edges."""
    out = None
    for n in SIZED:
        edges = GRAPHS[n](spark, sf).edges
        degrees = edges.select("src").union(edges.select("dst")).groupBy("src").count()
        one = degrees.agg(F.count(F.lit(1)).cast("double").alias("v"), (F.sum("count") / 2).cast("double").alias("e")).select(F.lit(n).alias("graph"), "v", "e")
        out = one if out is None else out.union(one)
    return out


_SIZES = "(" + " UNION ALL ".join(f"(WITH {edges_cte(n)} SELECT '{n}' AS graph, (SELECT count(DISTINCT id) FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e))::DOUBLE AS v, (SELECT count(*) FROM e)::DOUBLE AS e)" for n in SIZED) + ") t"


# --- layout -----------------------------------------------------------------------------------------------------------
_SIZING = [("one_interval", 4, 4, 2**30), ("small_memory", 4, 2, 2**14), ("eight_bytes", 8, 8, 2**16)]


@key("layout_beta", f"SELECT graph, label, greatest(1, ceil(phi * (t + 1) * v / m::DOUBLE))::BIGINT AS beta FROM {_SIZES}, (VALUES " + ", ".join(f"('{a}', {p}, {t}, {m})" for a, p, t, m in _SIZING) + ") x(label, phi, t, m)")
def layout_beta(spark, sf):
    """Intervals of graphs of the given tables under a few settings of value bytes, threads and memory."""
    rows = sizes(spark, sf).crossJoin(F.broadcast(spark.createDataFrame(_SIZING, "label string, phi long, t long, m long")))
    return rows.select("graph", "label", F.greatest(F.lit(1), F.ceil(F.col("phi") * (F.col("t") + 1) * F.col("v") / F.col("m"))).cast("long").alias("beta"))


@key("layout_intervals_hetero", f"WITH {edges_cte('hetero')} SELECT (id // ((n + 127) // 128))::INT AS p, count(*)::BIGINT AS theta, min(id) AS id_min, max(id) AS id_max FROM v, nv GROUP BY 1")
def layout_intervals(spark, sf):
    g = graph(spark, sf, "hetero")
    return lay.assign_intervals(g.vertices, "id", g.n, 128).groupBy("p").agg(F.count(F.lit(1)).alias("theta"), F.min("id").alias("id_min"), F.max("id").alias("id_max"))


@key("layout_intervals_mass_hetero", f"""WITH {edges_cte('hetero')}, d AS (SELECT dst AS id, count(*) AS c FROM e GROUP BY 1), m AS (SELECT id, c, (sum(c) OVER (ORDER BY id))::BIGINT - c AS below, (SELECT count(*) FROM e) AS total FROM d)
SELECT least(15, below * 16 // total)::INT AS p, min(id) AS first_id, max(id) AS last_id, sum(c)::BIGINT AS xi FROM m GROUP BY 1""")
def layout_mass(spark, sf):
    return lay.mass_intervals(graph(spark, sf, "hetero").edges, 16)


for _name in ("hetero", "copart_thin", "placed", "weblinks", "supply", "copart"):
    add(f"layout_blocks_{_name}", lambda spark, sf, n=_name: lay.block_stats(lay.blocked(graph(spark, sf, n).edges, graph(spark, sf, n).n, BETA[n])), f"WITH {blocks_sql(_name)} SELECT p, q, xi FROM b")
for _name in ("hetero", "copart_thin", "placed", "weblinks"):
    add(f"layout_modes_{_name}", lambda spark, sf, n=_name: modes(spark, sf, n).select("p", "q", "xi", F.round("crit", 9).alias("crit"), "mode"), f"WITH {modes_sql(_name)} SELECT p, q, xi, round(crit, 9) AS crit, mode FROM mm")

_SUMMARY = [("hetero", 64), ("hetero", 128), ("copart_thin", 16), ("placed", 64), ("weblinks", 64), ("purchase", 16)]


@key("layout_mode_summary", " UNION ALL ".join(f"(WITH {modes_sql(n, b)} SELECT '{n}' AS graph, {b} AS beta, mode, count(*)::BIGINT AS blocks, sum(xi)::BIGINT AS edges FROM mm GROUP BY mode)" for n, b in _SUMMARY))
def layout_mode_summary(spark, sf):
    out = None
    for n, b in _SUMMARY:
        part = modes(spark, sf, n, b).groupBy("mode").agg(F.count(F.lit(1)).alias("blocks"), F.sum("xi").alias("edges")).select(F.lit(n).alias("graph"), F.lit(b).alias("beta"), "mode", "blocks", "edges")
        out = part if out is None else out.union(part)
    return out


add("layout_source_partitions", lambda spark, sf: modes(spark, sf, "hetero").groupBy("p").agg(F.count(F.lit(1)).alias("blocks"), F.sum("xi").alias("edges")), f"WITH {blocks_sql('hetero')} SELECT p, count(*)::BIGINT AS blocks, sum(xi)::BIGINT AS edges FROM b GROUP BY p")
add("layout_dest_partitions", lambda spark, sf: modes(spark, sf, "hetero").groupBy("q").agg(F.count(F.lit(1)).alias("blocks"), F.sum("xi").alias("edges")), f"WITH {blocks_sql('hetero')} SELECT q, count(*)::BIGINT AS blocks, sum(xi)::BIGINT AS edges FROM b GROUP BY q")


@key("layout_materialised_roundtrip", f"WITH {modes_sql('copart_thin')} SELECT mode, count(*)::BIGINT AS edges, sum(src * 3 + dst * 7)::BIGINT AS checksum FROM g JOIN mm USING (p, q) GROUP BY mode")
def layout_roundtrip(spark, sf):
    layout = lay.build(graph(spark, sf, "copart_thin"), 16, bucketed=True, fused=False)
    parts = [x.select(F.lit(m).alias("mode"), "src", "dst") for m, x in (("dense", layout.dense), ("sparse", layout.sparse)) if x is not None]
    both = cut(parts[0] if len(parts) == 1 else parts[0].union(parts[1]), "roundtrip")
    layout.drop()
    return both.groupBy("mode").agg(F.count(F.lit(1)).alias("edges"), F.sum(F.col("src") * 3 + F.col("dst") * 7).alias("checksum"))


@key("zigzag_order", "WITH g AS (SELECT i + 1 AS step, (i // 7)::INT AS q, CASE WHEN (i // 7) % 2 = 0 THEN i % 7 ELSE 6 - i % 7 END::INT AS p FROM range(49) t(i)) SELECT step, q, p, coalesce(lag(p) OVER (ORDER BY step) = p, false) AS reused FROM g")
def zigzag_order(spark, sf):
    return schemes.zigzag(spark, 7).select("step", "q", F.col("p").cast("int").alias("p"), "reused")


# --- paths ------------------------------------------------------------------------------------------------------------
def _pr_start(spark, sf, name, mode="two_mode"):
    g = graph(spark, sf, name)
    layout, prog = lay.build(g, BETA[name], mode), alg.pagerank_program(g.n)
    return layout, prog, engine.start(layout, prog)


def _path_sql(mode: str) -> str:
    return f"WITH {modes_sql('hetero')}, d AS (SELECT src, count(*) AS c FROM e GROUP BY 1) SELECT g.q, g.dst, round(sum(1.0 / d.c) + 1e-9, 6) AS acc FROM g JOIN mm USING (p, q) JOIN d USING (src) WHERE mode = '{mode}' GROUP BY 1, 2"


@key("dense_path_messages_hetero", _path_sql("dense"))
def dense_messages(spark, sf):
    return schemes.dense(*_reorder(_pr_start(spark, sf, "hetero"))).select("q", "dst", F.round(F.col("acc0") + 1e-9, 6).alias("acc"))


@key("stream_path_messages_hetero", _path_sql("sparse"))
def stream_messages(spark, sf):
    layout, values, prog = _reorder(_pr_start(spark, sf, "hetero"))
    return schemes.fold(layout, schemes.emit(layout, values, prog), prog).select("q", "dst", F.round(F.col("acc0") + 1e-9, 6).alias("acc"))


def _reorder(x):
    return x[0], x[2], x[1]


@key("valued_edges_groups", f"WITH {blocks_sql('copart_thin')}, h AS (SELECT p, q, count(DISTINCT dst)::BIGINT AS groups FROM g GROUP BY 1, 2) SELECT p, q, xi, groups FROM b JOIN h USING (p, q)")
def valued_edges(spark, sf):
    g = graph(spark, sf, "copart_thin")
    per = lay.blocked(g.edges, g.n, 16).groupBy("p", "q", "dst").count()
    return per.groupBy("p", "q").agg(F.sum("count").alias("xi"), F.count(F.lit(1)).alias("groups"))


# --- PageRank ---------------------------------------------------------------------------------------------------------
def pagerank_sql(name: str, iters: int, normalized: bool = False, dangling: bool = False, out: str = "SELECT id, round(rank + 1e-9, 6) AS rank FROM r{n}", digits: int = 6) -> str:
    base, first = ("0.15 / (SELECT n FROM nv)", "1.0 / (SELECT n FROM nv)") if normalized else ("0.15", "1.0")
    text = f"WITH {edges_cte(name)}, d AS MATERIALIZED (SELECT src, count(*) AS c FROM e GROUP BY 1), r0 AS MATERIALIZED (SELECT id, ({first})::DOUBLE AS rank FROM v)"
    for i in range(1, iters + 1):
        lost = f" + 0.85 * coalesce((SELECT sum(rank) FROM r{i - 1} WHERE id NOT IN (SELECT src FROM d)), 0) / (SELECT n FROM nv)" if dangling else ""
        text += f", a{i} AS MATERIALIZED (SELECT e.dst AS id, sum(r.rank / d.c) AS acc FROM e JOIN r{i - 1} r ON e.src = r.id JOIN d ON d.src = e.src GROUP BY 1), r{i} AS MATERIALIZED (SELECT v.id, {base}{lost} + 0.85 * coalesce(acc, 0.0) AS rank FROM v LEFT JOIN a{i} USING (id))"
    return f"{text} {out.replace('{n}', str(iters))}"


def _rank(run: engine.Run) -> DataFrame:
    return run.values.select("id", F.round(F.col("rank") + 1e-9, 6).alias("rank"))


for _mode, _label in (("dense", "dense"), ("stream", "stream"), ("two_mode", "twomode")):
    add(f"pagerank_supply_{_label}", lambda spark, sf, m=_mode: _rank(alg.pagerank(graph(spark, sf, "supply"), 10, beta=16, scheme=m)), pagerank_sql("supply", 10))
add("pagerank_mass_rmat", lambda spark, sf: _rank(alg.pagerank(graph(spark, sf, "rmat"), 3, beta=32, how="mass")), pagerank_sql("rmat", 3))
add("pagerank_rmat_12", lambda spark, sf: _rank(alg.pagerank(graph(spark, sf, "rmat_12"), 1, beta=64)), pagerank_sql("rmat_12", 1))
for _name in ("copart", "purchase", "rmat"):
    add(f"pagerank_{_name}", lambda spark, sf, n=_name: _rank(alg.pagerank(graph(spark, sf, n), 10, beta=BETA[n])), pagerank_sql(_name, 10))
add("pagerank_hetero", lambda spark, sf: _rank(alg.pagerank(graph(spark, sf, "hetero"), 1, beta=128)), pagerank_sql("hetero", 1))
add("pagerank_hetero_10", lambda spark, sf: _rank(alg.pagerank(graph(spark, sf, "hetero"), 10, beta=128)), pagerank_sql("hetero", 10))
add("pagerank_network_rule", lambda spark, sf: _rank(alg.pagerank(graph(spark, sf, "hetero"), 2, beta=64, rule="network")), pagerank_sql("hetero", 2))
add("pagerank_normalized", lambda spark, sf: alg.pagerank(graph(spark, sf, "purchase"), 5, normalized=True, beta=16).values.select("id", F.round("rank", 9).alias("rank")), pagerank_sql("purchase", 5, normalized=True, out="SELECT id, round(rank, 9) AS rank FROM r{n}"))
add("pagerank_dangling", lambda spark, sf: _rank(alg.pagerank(graph(spark, sf, "purchase"), 5, dangling=True, beta=16)), pagerank_sql("purchase", 5, dangling=True))


@key("pagerank_tol", pagerank_sql("purchase", 6, out="SELECT id, round(rank + 1e-9, 6) AS rank, 2::BIGINT AS iterations FROM r{n}"))
def pagerank_tol(spark, sf):
    """Ranks settle exactly after two iterations here (edges lead from customers to parts only); the run stops by itself."""
    done = alg.pagerank(graph(spark, sf, "purchase"), 6, tol=1e-12, beta=16)
    return _rank(done).withColumn("iterations", F.lit(sum(c > 0 for c in done.changed)).cast("long"))


_RWR = f"WITH {edges_cte('purchase')}, d AS MATERIALIZED (SELECT src, count(*) AS c FROM e GROUP BY 1), r0 AS (SELECT id, CASE WHEN id % 100 = 0 THEN 1.0 ELSE 0.0 END::DOUBLE AS s FROM v)" + "".join(
    f", a{i} AS MATERIALIZED (SELECT e.dst AS id, sum(r.s / d.c) AS acc FROM e JOIN r{i - 1} r ON e.src = r.id JOIN d ON d.src = e.src GROUP BY 1), r{i} AS MATERIALIZED (SELECT v.id, 0.15 * CASE WHEN v.id % 100 = 0 THEN 1.0 ELSE 0.0 END + 0.85 * coalesce(acc, 0.0) AS s FROM v LEFT JOIN a{i} USING (id))"
    for i in range(1, 4)
)
add("rwr_purchase", lambda spark, sf: alg.rwr(graph(spark, sf, "purchase"), F.col("id") % 100 == 0, iters=3, beta=16).values.select("id", F.round(F.col("score") + 1e-9, 6).alias("score")), _RWR + " SELECT id, round(s + 1e-9, 6) AS score FROM r3")
add("spmv_weighted", lambda spark, sf: alg.spmv(graph(spark, sf, "supply"), F.lit(1.0), beta=16).select("id", F.round("y", 6).alias("y")), f"WITH {edges_cte('supply')} SELECT id, round(coalesce(sum(w), 0.0), 6) AS y FROM v LEFT JOIN e ON dst = id GROUP BY 1")
add("spmv_transpose", lambda spark, sf: alg.spmv(graph(spark, sf, "copart"), (F.col("id") % 7).cast("double"), transpose=False, beta=16).select("id", F.round("y", 6).alias("y")), f"WITH {edges_cte('copart')} SELECT id, round(coalesce(sum(w * (dst % 7)), 0.0), 6) AS y FROM v LEFT JOIN e ON src = id GROUP BY 1")

# --- components, traversal --------------------------------------------------------------------------------------------
for _name in ("hetero", "rmat"):
    add(f"wcc_iter1_{_name}", lambda spark, sf, n=_name: engine.run(graph(spark, sf, n).symmetric(), alg.wcc_program(), 1, beta=BETA[n]).values, f"WITH {edges_cte(_name, True)} SELECT id, least(id, coalesce(min(src), id)) AS label FROM v LEFT JOIN e ON dst = id GROUP BY id")


def wcc_sql(name: str, rounds: int, out: str = "SELECT id, label FROM l{n}") -> str:
    text = f"WITH {edges_cte(name, True)}, l0 AS MATERIALIZED (SELECT id, id AS label FROM v)"
    for i in range(1, rounds + 1):
        text += f", l{i} AS MATERIALIZED (SELECT v.id, least(any_value(o.label), coalesce(min(s.label), any_value(o.label))) AS label FROM v JOIN l{i - 1} o ON o.id = v.id LEFT JOIN e ON e.dst = v.id LEFT JOIN l{i - 1} s ON s.id = e.src GROUP BY v.id)"
    return f"{text} {out.replace('{n}', str(rounds))}"


_ROUNDS = {"placed": 3, "turns": 16, "dupdocs": 3, "copart_thin": 14}
for _key, _name, _method in (("wcc_stable_placed", "placed", "iterative"), ("wcc_turns", "turns", "iterative"), ("wcc_unionfind_dupdocs", "dupdocs", "unionfind"), ("wcc_unionfind_placed", "placed", "unionfind"), ("wcc_unionfind_copart_thin", "copart_thin", "unionfind"), ("wcc_contract_dupdocs", "dupdocs", "contract")):
    add(_key, lambda spark, sf, n=_name, m=_method: alg.wcc(graph(spark, sf, n), m, **({"beta": BETA[n]} if m == "iterative" else {})), wcc_sql(_name, _ROUNDS[_name]))
add("wcc_sizes", lambda spark, sf: alg.wcc(graph(spark, sf, "placed")).groupBy("label").agg(F.count(F.lit(1)).alias("size")), wcc_sql("placed", 3, "SELECT label, count(*)::BIGINT AS size FROM l{n} GROUP BY 1"))


@key("wcc_methods_agree", "SELECT unnest(['placed', 'dupdocs', 'weblinks']) AS graph, 0::BIGINT AS mismatches")
def wcc_methods_agree(spark, sf):
    out = None
    for n in ("placed", "dupdocs", "weblinks"):
        g = graph(spark, sf, n)
        a, b, c = (alg.wcc(g, m, **({"beta": 8} if m == "iterative" else {})) for m in ("iterative", "unionfind", "contract"))
        part = metrics.same_partition(a, b).unionAll(metrics.same_partition(a, c)).agg(F.sum("mismatches").alias("mismatches")).select(F.lit(n).alias("graph"), "mismatches")
        out = part if out is None else out.union(part)
    return out


_REACH = f"WITH RECURSIVE {edges_cte('turns')}, r(id, dist) AS (SELECT id, 0::BIGINT FROM v WHERE id = 0 UNION ALL SELECT e.dst, r.dist + 1 FROM r JOIN e ON e.src = r.id)"
add("bfs_turns", lambda spark, sf: alg.bfs(graph(spark, sf, "turns"), F.col("id") == 0, beta=8), _REACH + " SELECT v.id, min(dist) AS dist FROM v LEFT JOIN r USING (id) GROUP BY v.id")
add("sssp_transitions", lambda spark, sf: alg.sssp(graph(spark, sf, "transitions"), F.col("id") == 0, beta=1), f"WITH RECURSIVE {edges_cte('transitions')}, r(id, dist, hops) AS (SELECT id, 0.0::DOUBLE, 0 FROM v WHERE id = 0 UNION SELECT e.dst, r.dist + e.w, hops + 1 FROM r JOIN e ON e.src = r.id WHERE hops < 4) SELECT v.id, min(dist) AS dist FROM v LEFT JOIN r USING (id) GROUP BY v.id")
add("degrees_hetero", lambda spark, sf: alg.degrees(graph(spark, sf, "hetero")), f"WITH {edges_cte('hetero')} SELECT id, (SELECT count(*) FROM e WHERE dst = id)::BIGINT AS in_degree, (SELECT count(*) FROM e WHERE src = id)::BIGINT AS out_degree FROM v")
_CLOSURE = f"WITH RECURSIVE {edges_cte('turns')}, r(a, b, hops) AS (SELECT id, id, 0 FROM v UNION ALL SELECT r.a, e.dst, r.hops + 1 FROM r JOIN e ON e.src = r.b)"
add("diameter_turns", lambda spark, sf: alg.neighbourhood_exact(graph(spark, sf, "turns")).select("hops", "pairs"), _CLOSURE + ", h AS (SELECT hops, count(*) AS c FROM r GROUP BY 1) SELECT hops, (sum(c) OVER (ORDER BY hops))::BIGINT AS pairs FROM h")
add("neighbourhood_fn", lambda spark, sf: spark.createDataFrame(alg.neighbourhood_sketch(graph(spark, sf, "turns"), beta=8), "hops int, pairs double"))
@key("diameter_effective_turns", _CLOSURE + """, h AS (SELECT hops, count(*) AS c FROM r GROUP BY 1), m AS (SELECT hops, sum(c) OVER (ORDER BY hops) AS pairs, sum(c) OVER () AS whole FROM h),
f AS (SELECT min(hops) AS hops FROM m WHERE pairs >= 0.9::DOUBLE * whole)
SELECT round(CASE WHEN f.hops = 0 THEN 0 ELSE f.hops - 1 + (0.9::DOUBLE * a.whole - b.pairs) / (a.pairs - b.pairs) END, 9)::DOUBLE AS effective, (SELECT max(hops) FROM m)::BIGINT AS diameter
FROM f JOIN m a ON a.hops = f.hops LEFT JOIN m b ON b.hops = f.hops - 1""")
def diameter_effective(spark, sf):
    return spark.createDataFrame([alg.diameter(graph(spark, sf, "turns"), exact=True)], "effective double, diameter long").withColumn("effective", F.round("effective", 9))


@key("diameter_sketch_turns", "SELECT true AS diameter_ok, true AS effective_ok, true AS pairs_ok")
def diameter_sketch(spark, sf):
    """The sketched neighbourhood function against the exact one: same diameter, effective diameter within one hop, pairs within 30 %."""
    g = graph(spark, sf, "turns")
    exact = [float(r.pairs) for r in alg.neighbourhood_exact(g).orderBy("hops").collect()]
    grown = alg.neighbourhood_sketch(g, registers=32, beta=8)
    (effective, last), (about, reach) = alg.effective_diameter(list(enumerate(exact))), alg.effective_diameter(grown)
    return spark.createDataFrame([(reach == last, abs(about - effective) <= 1, all(abs(m / exact[min(h, len(exact) - 1)] - 1) < 0.3 for h, m in grown))], "diameter_ok boolean, effective_ok boolean, pairs_ok boolean")


add("triangles_exact", lambda spark, sf: alg.triangles(graph(spark, sf, "copart_thin")), f"WITH {edges_cte('copart_thin', True)}, u AS (SELECT src, dst FROM e WHERE src < dst) SELECT count(*)::BIGINT AS triangles FROM u a JOIN u b ON a.src = b.src JOIN u c ON c.src = a.dst AND c.dst = b.dst")

add("triangles_copart", lambda spark, sf: alg.triangles(graph(spark, sf, "copart")), f"WITH {edges_cte('copart', True)}, u AS (SELECT src, dst FROM e WHERE src < dst) SELECT count(*)::BIGINT AS triangles FROM u a JOIN u b ON a.src = b.src JOIN u c ON c.src = a.dst AND c.dst = b.dst")
add("wcc_unionfind_copart", lambda spark, sf: alg.wcc(graph(spark, sf, "copart"), "unionfind"))


# --- eigensolver, vectors ---------------------------------------------------------------------------------------------
def power_sql(name: str, iters: int) -> str:
    text = f"WITH {edges_cte(name)}, x0 AS MATERIALIZED (SELECT id, 1 / sqrt((SELECT n FROM nv)) AS x FROM v)"
    for i in range(1, iters + 1):
        text += f", y{i} AS MATERIALIZED (SELECT v.id, coalesce(sum(e.w * x.x), 0.0) AS y FROM v LEFT JOIN e ON e.src = v.id LEFT JOIN x{i - 1} x ON x.id = e.dst GROUP BY v.id), x{i} AS MATERIALIZED (SELECT id, y / (SELECT sqrt(sum(y * y)) FROM y{i}) AS x FROM y{i})"
    return f"{text} SELECT round(sum(x.x * y.y), 4) AS lambda1 FROM x{iters - 1} x JOIN y{iters} y USING (id)"


add("power_iteration_copart", lambda spark, sf: spark.createDataFrame([(lanczos.power_iteration(graph(spark, sf, "copart"), 6),)], "v double").select(F.round("v", 4).alias("lambda1")), power_sql("copart", 6))
@key("lanczos_copart_top")
def lanczos_copart_top(spark, sf):
    """The 20 eigenvalues of largest magnitude after 30 steps, and whether each has converged by its residual bound. All 20 do with
    ``tol`` in place of a number of steps, which takes some hundreds of them on this graph."""
    found = lanczos.eigenpairs(graph(spark, sf, "copart"), 20, 30)
    return spark.createDataFrame([(i + 1, round(float(v), 3), bool(r <= 1e-6 * abs(v))) for i, (v, r) in enumerate(zip(found.values, found.residuals, strict=True))], "rank int, eigenvalue double, converged boolean")


@key("lanczos_residual_ok", "SELECT unnest(['selective', 'full']) AS reorth, true AS top_residual_ok, true AS basis_ok")
def lanczos_residual_ok(spark, sf):
    """The leading pair and the basis of the co-purchase graph after a few steps, by both ways of keeping vectors apart."""
    g, rows = graph(spark, sf, "copart"), []
    matrix = lanczos.Matrix(g)
    for reorth in ("selective", "full"):
        found = lanczos.eigenpairs(g, 1, reorth=reorth, tol=1e-6, matrix=matrix)
        rows.append((reorth, lanczos.residuals(matrix, found)[0] < 2e-6, metrics.ortho_loss(found.basis) < 1e-6))
    matrix.drop()
    return spark.createDataFrame(rows, "reorth string, top_residual_ok boolean, basis_ok boolean")


@key("lanczos_ortho")
def lanczos_ortho(spark, sf):
    g = graph(spark, sf, "knn").symmetric()
    return spark.createDataFrame([(r, float(metrics.ortho_loss(lanczos.eigenpairs(g, 3, 8, r).basis))) for r in ("selective", "full", "none")], "reorth string, loss double")


add("svd_supply", lambda spark, sf: spark.createDataFrame([(i + 1, float(v)) for i, v in enumerate(lanczos.svd(graph(spark, sf, "supply"), 3, 8))], "rank int, sigma double"))
add("spectral_knn", lambda spark, sf: lanczos.spectral_clusters(graph(spark, sf, "knn"), 4).groupBy("cluster").agg(F.count(F.lit(1)).alias("size")))
add("triangles_spectral", lambda spark, sf: spark.createDataFrame([(lanczos.triangles_spectral(graph(spark, sf, "copart_thin"), 5),)], "estimate double"))


@key("tensor_cp_als")
def tensor_cp_als(spark, sf):
    """Customers, parts and suppliers of all lines: rank 2, explained share and rows of the factors."""
    counts = table(spark, sf, "orders").join(table(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy(F.col("o_custkey").alias("i"), F.col("l_partkey").alias("j"), F.col("l_suppkey").alias("k")).agg(F.count(F.lit(1)).cast("double").alias("x"))
    factors, told = alg.cp_als(cut(counts, "tensor"), 2, 2)
    return spark.createDataFrame([(m, f.count(), told) for m, f in factors.items()], "mode string, rows long, explained double")


def _balances(spark, sf):
    c = table(spark, sf, "customer")
    return c.select(F.col("c_custkey").alias("id"), F.col("c_acctbal").alias("x")), c.select(F.col("c_custkey").alias("id"), (F.col("c_custkey") % 5).cast("double").alias("x"))


add("vec_dot", lambda spark, sf: vo.dot(*_balances(spark, sf)).select(F.round("value", 4).alias("value")), "SELECT round(sum(c_acctbal * (c_custkey % 5)), 4) AS value FROM customer")
add("vec_norm", lambda spark, sf: vo.norm2(_balances(spark, sf)[0]).select(F.round("value", 4).alias("value")), "SELECT round(sqrt(sum(c_acctbal * c_acctbal)), 4) AS value FROM customer")
add("vec_axpy", lambda spark, sf: vo.axpy(0.5, *_balances(spark, sf)).select("id", F.round("x", 6).alias("x")), "SELECT c_custkey AS id, round(0.5::DOUBLE * c_acctbal + c_custkey % 5, 6) AS x FROM customer")
add("vec_scale", lambda spark, sf: vo.scale(2.0, _balances(spark, sf)[0]).select("id", F.round("x", 6).alias("x")), "SELECT c_custkey AS id, round(2.0::DOUBLE * c_acctbal, 6) AS x FROM customer")
add("vec_gram", lambda spark, sf: vo.gram([*_balances(spark, sf)]).select("i", "j", F.round("value", 3).alias("value")), "SELECT 0 AS i, 0 AS j, round(sum(c_acctbal * c_acctbal), 3) AS value FROM customer UNION ALL SELECT 0, 1, round(sum(c_acctbal * (c_custkey % 5)), 3) FROM customer UNION ALL SELECT 1, 1, round(sum((c_custkey % 5)::DOUBLE * (c_custkey % 5)), 3) FROM customer")

# --- baselines --------------------------------------------------------------------------------------------------------
for _name in ("sorted_shards", "scatter_gather", "adjacency_index", "cached_dedicated", "uniform_grid", "naive"):
    add(f"baseline_{_name}", lambda spark, sf, n=_name: getattr(baselines, n)(graph(spark, sf, "supply"), 3).select("id", F.round(F.col("rank") + 1e-9, 6).alias("rank")), pagerank_sql("supply", 3))

@key("wcc_scatter_gather_placed", wcc_sql("placed", 3))
def wcc_scatter(spark, sf):
    """Components by the stand-in that scans, writes and reads all updates in every iteration."""
    return baselines.wcc_scatter_gather(graph(spark, sf, "placed"))


add("wcc_dedicated_placed", lambda spark, sf: baselines.wcc_dedicated(graph(spark, sf, "placed")), wcc_sql("placed", 3))


@key("plan_scans", "SELECT plan, scans::INT AS scans FROM (VALUES ('dense', 2), ('stream', 2), ('scatter_gather', 3)) t(plan, scans)")
def plan_scans(spark, sf):
    """File scans of vertex values and edges in one iteration: of the two paths once each, of the stand-in that writes its updates three."""
    g = graph(spark, sf, "supply")
    rows = []
    with settings(spark, **engine.PLAN):
        for mode in ("dense", "stream"):
            layout = lay.build(g, 16, mode)
            prog = alg.pagerank_program(g.n)
            values, _ = engine.generation(layout, engine.start(layout, prog))
            path = schemes.dense(layout, values, prog) if mode == "dense" else schemes.emit(layout, values, prog)
            rows.append((mode, metrics.scans(path.drop("p"), ("edges", "generation"))))
    rows.append(("scatter_gather", baselines.scatter_gather_scans(g)))
    return spark.createDataFrame(rows, "plan string, scans int")


# --- cost, simulation -------------------------------------------------------------------------------------------------
_PAPER = "(VALUES " + ", ".join(f"('{g}', {v}::DOUBLE, {e}::DOUBLE)" for g, v, e in simulate.PAPER_GRAPHS) + ") t(graph, v, e)"
add("cost_graph_dense", lambda spark, sf: sizes(spark, sf).crossJoin(F.broadcast(spark.createDataFrame([(float(b),) for b in (1, 4, 23, 64)], "beta double"))).select("graph", "beta", cm.dense_graph(F.col("v"), F.col("e"), F.col("beta")).alias("cost")), f"SELECT graph, beta, (beta * v + v + e) + beta * beta AS cost FROM {_SIZES}, (SELECT unnest([1.0::DOUBLE, 4, 23, 64]) AS beta)")
add("cost_graph_stream", lambda spark, sf: sizes(spark, sf).crossJoin(F.broadcast(spark.createDataFrame([(float(b),) for b in (1, 4, 23, 64)], "beta double"))).select("graph", "beta", cm.stream_graph(F.col("v"), F.col("e"), F.col("e"), F.col("beta")).alias("cost")), f"SELECT graph, beta, (2 * v + e + 2 * e) + beta AS cost FROM {_SIZES}, (SELECT unnest([1.0::DOUBLE, 4, 23, 64]) AS beta)")
_BLOCK_COST = "xi, width::DOUBLE * 4 * (1 + 1.0::DOUBLE / 128) + xi * 8 AS dense_cost, 2 * width::DOUBLE * 4 / 128 + 2 * xi * 12 + xi * 8 AS stream_cost"


@key("cost_blocks_hetero", f"WITH {blocks_sql('hetero')}, c AS (SELECT p, q, {_BLOCK_COST} FROM b, k) SELECT p, q, round(dense_cost, 6) AS dense_cost, round(stream_cost, 6) AS stream_cost FROM c")
def cost_blocks(spark, sf):
    g = graph(spark, sf, "hetero")
    w = float(lay.width_of(g.n, 128))
    return modes(spark, sf, "hetero").select("p", "q", F.round(cm.dense_block(F.col("xi"), w, 128.0), 6).alias("dense_cost"), F.round(cm.stream_block(F.col("xi"), w, 128.0), 6).alias("stream_cost"))


@key("cost_twomode", f"WITH {blocks_sql('hetero')}, c AS (SELECT {_BLOCK_COST} FROM b, k) SELECT 'hetero' AS graph, 128 AS beta, round(sum(dense_cost), 3) AS dense, round(sum(stream_cost), 3) AS stream, round(sum(least(dense_cost, stream_cost)), 3) AS two_mode FROM c")
def cost_twomode(spark, sf):
    g = graph(spark, sf, "hetero")
    return cm.two_mode_cost(modes(spark, sf, "hetero"), 128, lay.width_of(g.n, 128)).select(F.lit("hetero").alias("graph"), F.lit(128).alias("beta"), *(F.round(c, 3).alias(c) for c in ("dense", "stream", "two_mode")))


@key("cost_transfers_seeks", f"SELECT graph, scheme, CASE scheme WHEN 'dense' THEN (24 * v + e) / 4096 ELSE (2 * v + 3 * e) / 4096 END AS transfers, CASE scheme WHEN 'dense' THEN 529.0::DOUBLE ELSE 23.0::DOUBLE END AS seeks FROM {_SIZES}, (SELECT unnest(['dense', 'stream']) AS scheme)")
def cost_transfers(spark, sf):
    """Transferred blocks of 4096 elements and jumps, apart, for 23 intervals."""
    io = {k: cm.graph_io(k, F.col("v"), F.col("e"), 23, 4096) for k in ("dense", "stream")}
    kinds = F.explode(F.array(*(F.struct(F.lit(k).alias("scheme"), c.transfers.alias("transfers"), F.lit(float(c.seeks)).alias("seeks")) for k, c in io.items()))).alias("x")
    return sizes(spark, sf).select("graph", kinds).select("graph", "x.*")


@key("layout_beta_cluster", "SELECT v, greatest(1, ceil(4.0::DOUBLE * 5 * v / (gib * 1073741824::DOUBLE * 0.5)))::BIGINT AS beta FROM (SELECT unnest([1000000000, 100000000000])::BIGINT AS v), (SELECT 32 AS gib)")
def layout_beta_cluster(spark, sf):
    return spark.createDataFrame([(v, cm.num_intervals_cluster(v, 4, 4, 32 * 2**30)) for v in (10**9, 10**11)], "v long, beta long")


_BETAS = [2, 3, 13, 21, 61, 128]


@key("criterion_equivalence", "SELECT sum(blocks)::BIGINT AS blocks, 0::BIGINT AS disagreements FROM (" + " UNION ALL ".join(f"(WITH {blocks_sql(n, b)} SELECT 6 * count(*) AS blocks FROM b)" for n in ("placed", "usage") for b in _BETAS) + ")")
def criterion_equivalence(spark, sf):
    """Over the blocks of graphs of the given tables, in whole numbers: criterion < 1 exactly where the streamed block costs less."""
    blocks = None
    for n in ("placed", "usage"):
        g = GRAPHS[n](spark, sf)
        for b in _BETAS:
            one = lay.block_stats(lay.blocked(g.edges, g.n, b)).select("xi", F.lit(lay.width_of(g.n, b)).cast("long").alias("theta"), F.lit(b).cast("long").alias("beta"))
            blocks = one if blocks is None else blocks.union(one)
    grid = blocks.crossJoin(F.broadcast(simulate.grid(spark, phi=[4, 8], psi=[4, 8, 12])))
    xi, th, be, ph, ps = (F.col(c) for c in ("xi", "theta", "beta", "phi", "psi"))
    crit = th * ph + 2 * xi * be * (ph + ps) < th * be * ph
    cheaper = 2 * th * ph + 2 * xi * (ph + ps) * be + xi * ps * be < th * ph * be + th * ph + xi * ps * be
    return grid.agg(F.count(F.lit(1)).alias("blocks"), F.coalesce(F.sum(F.when(crit != cheaper, 1).otherwise(0)), F.lit(0)).cast("long").alias("disagreements"))


add("preprocess_cost", lambda spark, sf: simulate.paper_graphs(spark).select("graph", cm.preprocess_cost(F.col("e")).alias("cost")), f"SELECT graph, 4 * e AS cost FROM {_PAPER}")
add("tcost_unit", lambda spark, sf: simulate.paper_graphs(spark).select("graph", cm.tcost_unit(F.col("v"), F.col("e")).alias("cost")), f"SELECT graph, 2 * v + e AS cost FROM {_PAPER}")
_GIB = [0.25, 1, 4, 8, 16]
_MIB = [0.25, 1, 4, 8, 16]  # tables are smaller than the published graphs
add("beta_by_memory", lambda spark, sf: sizes(spark, sf).crossJoin(F.broadcast(spark.createDataFrame([(float(m),) for m in _MIB], "mib double"))).select("graph", "mib", simulate.beta_column(F.col("v"), F.col("mib") * 2**20).alias("beta")), f"SELECT graph, mib, greatest(1, ceil(20 * v / (mib * 1048576)))::BIGINT AS beta FROM {_SIZES}, (SELECT unnest({_MIB}::DOUBLE[]) AS mib)")
_TCOST = "CASE scheme WHEN 'dense' THEN least(d, 1e300) WHEN 'stream' THEN s ELSE least(d, s) END"
add("tcost_memory_paper", lambda spark, sf: simulate.memory_curve(simulate.paper_graphs(spark), _GIB).select("graph", "gib", "scheme", F.round("tcost", 6).alias("tcost")),
    f"WITH g AS (SELECT graph, gib, v, e, greatest(1, ceil(20 * v / (gib * 1073741824))) AS beta FROM {_PAPER}, (SELECT unnest({_GIB}::DOUBLE[]) AS gib)), c AS (SELECT graph, gib, ((beta + 1) * v + e) / (2 * v + e) AS d, (2 * v + 3 * e) / (2 * v + e) AS s FROM g) SELECT graph, gib, scheme, round({_TCOST}, 6) AS tcost FROM c, (SELECT unnest(['dense', 'stream', 'two_mode']) AS scheme)")


def _ours(graphs, betas):
    return " UNION ALL ".join(
        f"(WITH {blocks_sql(n, b)}, c AS (SELECT width::DOUBLE * 4 * (1 + 1.0::DOUBLE / {b}) + xi * 8 AS d, 2 * width::DOUBLE * 4 / {b} + 2 * xi * 12 + xi * 8 AS s FROM b, k), t AS (SELECT sum(d) AS dense, sum(s) AS stream, sum(least(d, s)) AS two_mode FROM c) SELECT '{n}' AS graph, {b} AS beta, scheme, round(CASE scheme WHEN 'dense' THEN dense WHEN 'stream' THEN stream ELSE two_mode END, 3) AS tcost FROM t, (SELECT unnest(['dense', 'stream', 'two_mode']) AS scheme))"
        for n in graphs for b in betas)


def _ours_rows(spark, sf, graphs, betas):
    out = None
    for n in graphs:
        for b in betas:
            g = graph(spark, sf, n)
            one = cm.two_mode_cost(modes(spark, sf, n, b), b, lay.width_of(g.n, b)).unpivot([], ["dense", "stream", "two_mode"], "scheme", "cost")
            one = one.select(F.lit(n).alias("graph"), F.lit(b).alias("beta"), "scheme", F.round("cost", 3).alias("tcost"))
            out = one if out is None else out.union(one)
    return out


add("tcost_memory_ours", lambda spark, sf: _ours_rows(spark, sf, ("hetero", "copart_thin"), (4, 16, 64)), _ours(("hetero", "copart_thin"), (4, 16, 64)))
add("tcost_density_ours", lambda spark, sf: _ours_rows(spark, sf, ("copart_thin", "weblinks", "knn", "usage"), (2, 8, 16)), _ours(("copart_thin", "weblinks", "knn", "usage"), (2, 8, 16)))
add("tcost_density", lambda spark, sf: simulate.density_curve(spark, [3, 5, 10, 30], [1, 2, 5, 10, 20, 50, 100, 150]).select("k", "beta", "scheme", F.round("tcost", 6).alias("tcost"), "chosen"),
    "WITH g AS (SELECT k, beta, (beta + 1 + k) / (2 + k) AS d, (2 + 3 * k) / (2 + k) AS s FROM (SELECT unnest([3, 5, 10, 30]::DOUBLE[]) AS k), (SELECT unnest([1, 2, 5, 10, 20, 50, 100, 150]::DOUBLE[]) AS beta)) SELECT k, beta, scheme, round(CASE scheme WHEN 'dense' THEN d WHEN 'stream' THEN s ELSE least(d, s) END, 6) AS tcost, CASE WHEN s < d THEN 'stream' ELSE 'dense' END AS chosen FROM g, (SELECT unnest(['dense', 'stream', 'two_mode']) AS scheme)")
@key("crossover", f"SELECT graph, psi, round(1 + 2 * (e / v) * (1 + psi / 4.0::DOUBLE), 6) AS beta_star, round(1 + 2 * (e / v), 6) AS beta_star_elements FROM {_SIZES}, (SELECT unnest([4, 8])::BIGINT AS psi)")
def crossover(spark, sf):
    """From how many intervals on blocks are sparse, by the density of graphs of the given tables."""
    k = F.col("e") / F.col("v")
    rows = sizes(spark, sf).crossJoin(F.broadcast(simulate.grid(spark, psi=[4, 8])))
    return rows.select("graph", "psi", F.round(cm.crossover(k, 4, F.col("psi")), 6).alias("beta_star"), F.round(cm.crossover_elements(k), 6).alias("beta_star_elements"))


add("zigzag_loads", lambda spark, sf: simulate.zigzag_measured(spark, [1, 2, 3, 7, 16]), "SELECT beta, beta * beta - beta + 1 AS loads, beta - 1 AS saved FROM (SELECT unnest([1, 2, 3, 7, 16])::BIGINT AS beta)")


@key("network_rows", " UNION ALL ".join(
    f"(WITH {modes_sql('hetero', b)}, sd AS (SELECT p, q, count(DISTINCT src) AS s, count(DISTINCT dst) AS d FROM g GROUP BY 1, 2) SELECT {b} AS beta, sum(d)::BIGINT AS stream, (count(*) * any_value(width))::BIGINT AS dense, sum(s)::BIGINT AS filtered, sum(CASE WHEN mode = 'dense' THEN width ELSE d END)::BIGINT AS printed_rule, sum(least(s, d))::BIGINT AS smaller_side FROM sd JOIN mm USING (p, q), k)"
    for b in (16, 64)))
def network_rows(spark, sf):
    out = None
    for b in (16, 64):
        g = graph(spark, sf, "hetero")
        one = metrics.exchange_rows(g, b)
        out = one if out is None else out.union(one)
    return out


_RUNTIME = "(VALUES " + ", ".join(f"('{w}', '{s}', {t}::DOUBLE)" for w, s, t in simulate.RUNTIMES) + ") r(workload, system, seconds)"
add("speedup_paper_table", lambda spark, sf: simulate.speedups(spark).select("workload", "system", F.round("speedup", 4).alias("speedup")), f"SELECT a.workload, a.system, round(a.seconds / b.seconds, 4) AS speedup FROM {_RUNTIME.replace(' r(', ' a(')} JOIN {_RUNTIME.replace(' r(', ' b(')} ON a.workload = b.workload AND b.system = 'engine' WHERE a.system <> 'engine'")
add("total_one_iteration_paper", lambda spark, sf: simulate.totals(spark), "SELECT system, p + r AS total FROM (VALUES " + ", ".join(f"('{s}', {p}::DOUBLE, {r}::DOUBLE)" for s, p, r in simulate.GL_PREPARE_AND_RUN) + ") t(system, p, r)")
