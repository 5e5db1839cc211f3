"""Worked examples, decisions, layouts, schemes, algorithms, plans and edge cases of the graph engine."""

from fractions import Fraction

import numpy as np
import pytest
from hypothesis import given, settings as hyp
from hypothesis import strategies as st
from pyspark.sql import functions as F

from blockgraph.operators import algorithms as alg
from blockgraph.operators import baselines, lanczos
from blockgraph.plans import costmodel as cm
from blockgraph.plans import engine, layout as lay, metrics, schemes, simulate
from blockgraph.sources.graphs import Graph, hetero, placed
from blockgraph.storage import settings


def test_sizing_example_and_units():
    assert cm.num_intervals(2_000_000_000, 4, 2, 2**30) == 23 and 23**2 == 529
    assert [cm.tcost_unit(v, e) for _, v, e in simulate.PAPER_GRAPHS] == [78_688_915, 1_551_669_642, 9_463_623_561, 20_000_000_000]
    assert [cm.crossover(k, 4, 4) for k in (3, 5, 10, 30)] == [13, 21, 41, 121]
    assert [cm.crossover(k, 4, 8) for k in (3, 5, 10, 30)] == [19, 31, 61, 181]
    assert [cm.crossover_elements(k) for k in (3, 5, 10, 30)] == [7, 11, 21, 61]
    assert [max(1, cm.num_intervals(1_413_511_391, 4, 4, g * 2**30)) for g in (0.25, 1, 4, 8, 16)] == [106, 27, 7, 4, 2]
    assert cm.num_intervals_cluster(625_000_000_000, 8, 8, 32 * 2**30, 1.0) == 1310


@hyp(max_examples=300, deadline=None)
@given(st.integers(0, 5000), st.integers(1, 2000), st.integers(1, 200), st.sampled_from([4, 8, 16]), st.sampled_from([4, 8, 12]))
def test_criterion_is_the_cheaper_cost(xi, theta, beta, phi, psi):
    dense = Fraction(theta * phi) * (1 + Fraction(1, beta)) + xi * psi
    stream = Fraction(2 * theta * phi, beta) + 2 * xi * (phi + psi) + xi * psi
    crit = Fraction(1, beta) + Fraction(2 * xi, theta) * (1 + Fraction(psi, phi))
    assert (crit < 1) == (stream < dense)
    assert not (beta == 1 and crit < 1)


TOY = [(0, 1), (1, 4), (2, 8), (4, 0), (3, 3), (5, 7), (6, 2), (8, 4), (8, 4), (0, 1)]


@pytest.fixture(scope="module")
def toy(spark):
    return Graph("toy", 9, spark.createDataFrame(TOY, "src long, dst long"))


def test_toy_blocks_and_zigzag(spark, toy):
    b = {(r.p, r.q): r.xi for r in lay.block_stats(lay.blocked(toy.edges, 9, 3)).collect()}
    assert b == {(0, 0): 2, (0, 1): 1, (0, 2): 1, (1, 0): 1, (1, 1): 1, (1, 2): 1, (2, 0): 1, (2, 1): 2}
    layout = lay.build(toy, 3)
    assert sorted((r.src, r.dst) for r in layout.source_partition(0).collect()) == [(0, 1), (0, 1), (1, 4), (2, 8)]
    assert sorted((r.src, r.dst) for r in layout.destination_partition(2).collect()) == [(2, 8), (5, 7)]
    order = schemes.zigzag(spark, 3).orderBy("step").collect()
    assert [r.p for r in order] == [0, 1, 2, 2, 1, 0, 0, 1, 2] and sum(not r.reused for r in order) == 7


def dense_pagerank(n, edges, iters):
    out = np.bincount([s for s, _ in edges], minlength=n)
    r = np.ones(n)
    for _ in range(iters):
        new = np.full(n, 0.15)
        for s, d in edges:
            new[d] += 0.85 * r[s] / out[s]
        r = new
    return r


def ranks(values):
    return {r.id: r["rank"] for r in values.collect()}


@pytest.mark.parametrize("scheme", ["dense", "stream", "two_mode"])
@pytest.mark.parametrize("beta", [1, 3, 4, 20])
def test_schemes_agree_on_the_toy_graph(toy, scheme, beta):
    got = ranks(alg.pagerank(toy, 3, beta=beta, scheme=scheme).values)
    assert np.allclose([got[i] for i in range(9)], dense_pagerank(9, TOY, 3))


@pytest.mark.parametrize("bucketed", [False, True])
def test_mixed_layout_and_baselines(spark, sf, bucketed):
    g = hetero(spark, sf)
    layout = lay.build(g, 64, bucketed=bucketed)
    modes = {r["mode"]: r for r in layout.blocks.groupBy("mode").agg(F.count("*").alias("blocks"), F.sum("xi").alias("edges")).collect()}
    assert (modes["dense"].blocks, modes["dense"].blocks + modes["sparse"].blocks) == (550, 612)
    assert modes["dense"].edges + modes["sparse"].edges == g.edges.count()
    run = engine.iterate(layout, alg.pagerank_program(g.n), 2)
    naive = baselines.naive(g, 2)
    assert metrics.max_abs_diff(run.values, naive, "rank") < 1e-9
    if not bucketed:
        for other in (baselines.sorted_shards, baselines.scatter_gather, baselines.adjacency_index, baselines.cached_dedicated, baselines.uniform_grid):
            assert metrics.max_abs_diff(other(g, 2), naive, "rank") < 1e-9, other.__name__
    layout.drop()


def test_plan_of_an_iteration_moves_no_edge(spark, sf):
    g = hetero(spark, sf)
    layout = lay.build(g, 64, bucketed=True)
    prog = alg.pagerank_program(g.n)
    with settings(spark, **engine.PLAN, spark__sql__adaptive__enabled="false"):
        values, _ = engine.generation(layout, engine.start(layout, prog))
        assert metrics.exchanges(schemes.dense(layout, values, prog)) == 1
        whole = schemes.two_mode(layout, values, prog)
        assert metrics.exchanges(whole) == 2
    layout.drop()


def test_preprocessing_in_two_passes_and_rules(spark, sf):
    g = placed(spark, sf)
    one, two = lay.build(g, 16), lay.build(g, 16, fused=False)
    assert sorted(map(tuple, one.blocks.collect())) == sorted(map(tuple, two.blocks.collect()))
    a = lay.build(g, 16, rule="argmin").blocks.select("p", "q", "mode")
    assert not a.exceptAll(one.blocks.select("p", "q", "mode")).count()
    mass = lay.mass_intervals(g.edges, 4, "src").collect()
    assert sum(r.xi for r in mass) == g.edges.count() and max(r.xi for r in mass) < 2 * g.edges.count() / 4


EDGE_CASES = {"empty": (4, []), "one": (1, []), "loop": (1, [(0, 0)]), "isolated": (5, [(0, 1)]), "chain": (6, [(i, i + 1) for i in range(5)]), "two": (7, [(0, 1), (1, 2), (4, 5), (5, 4), (4, 5)])}


def test_components_of_large_tables_go_another_way(spark):
    from blockgraph.operators import components as comp

    r = np.random.default_rng(3)
    edges = spark.createDataFrame([tuple(map(int, e)) for e in r.integers(0, 300, (220, 2))], "a long, b long")
    small = {tuple(x) for x in comp.components(edges).collect()}
    assert {tuple(x) for x in comp.components(edges, small=0).collect()} == small


@pytest.mark.parametrize("name", EDGE_CASES)
def test_edge_cases(spark, name):
    n, edges = EDGE_CASES[name]
    g = Graph(name, n, spark.createDataFrame(edges, "src long, dst long"))
    got = ranks(alg.pagerank(g, 2, beta=3).values)
    assert np.allclose([got[i] for i in range(n)], dense_pagerank(n, edges, 2))
    label = list(range(n))
    for _ in range(n):
        for s, d in edges:
            label[s] = label[d] = min(label[s], label[d])
    for method, more in (("iterative", {"beta": 2}), ("unionfind", {}), ("contract", {})):
        assert [r.label for r in alg.wcc(g, method, **more).orderBy("id").collect()] == label


def test_spectrum_of_known_graphs(spark):
    n = 6
    clique = Graph("clique", n, spark.createDataFrame([(i, j) for i in range(n) for j in range(n) if i != j], "src long, dst long"))
    found = lanczos.eigenpairs(clique, 1, 4, "full")
    assert abs(found.values[0] - (n - 1)) < 1e-6
    assert metrics.residual(lanczos.product(clique.edges, False), found.vectors()[0], float(found.values[0])) < 1e-6
    assert abs(lanczos.power_iteration(clique, 3) - (n - 1)) < 1e-9
    assert alg.triangles(clique).first()[0] == 20


@pytest.mark.parametrize("block", [1, 4])
def test_all_wanted_pairs_converge(spark, block):
    """Against numpy, on a graph with weights: values, true residuals; and a step's vectors are taken away."""
    r = np.random.default_rng(2)
    a = np.triu(r.random((24, 24)) * (r.random((24, 24)) < 0.4), 1)
    a = a + a.T
    g = Graph("random", 24, spark.createDataFrame([(i, j, float(a[i, j])) for i in range(24) for j in range(24) if a[i, j]], "src long, dst long, w double"), True)
    matrix = lanczos.Matrix(g, beta=3)
    found = lanczos.eigenpairs(g, 4, tol=1e-7, matrix=matrix, block=block)
    want = np.linalg.eigvalsh(a)
    assert np.allclose(found.values, want[np.argsort(-np.abs(want))][:4], rtol=1e-8)
    assert max(lanczos.residuals(matrix, found)) < 1e-6 and len(found.seconds) < 24


def test_singular_values(spark):
    r = np.random.default_rng(3)
    a = (r.random((9, 9)) < 0.4) * 1.0
    g = Graph("random", 9, spark.createDataFrame([(i, j, 1.0) for i in range(9) for j in range(9) if a[i, j]], "src long, dst long, w double"), True)
    assert np.allclose(lanczos.svd(g, 2, 9), np.linalg.svd(a, compute_uv=False)[:2], atol=1e-6)


def test_tensor_over_ids_of_any_size(spark):
    """A tensor of rank one is explained whole; ids are far apart."""
    u, v, w = {10**12: 1.0, 5: 2.0}, {7: 3.0, -4: 1.0, 10**15: 2.0}, {0: 1.0, 9: 5.0}
    counts = spark.createDataFrame([(i, j, k, u[i] * v[j] * w[k]) for i in u for j in v for k in w], "i long, j long, k long, x double")
    factors, told = alg.cp_als(counts, 1, 3)
    assert abs(told - 1) < 1e-9 and {m: f.count() for m, f in factors.items()} == {"i": 2, "j": 3, "k": 2}


def test_intervals_by_mass_and_a_hub(spark):
    """A third of all edges end in one vertex: intervals by mass are smaller there, results are the same."""
    from blockgraph.sources.graphs import rmat

    base = rmat(spark, 8, 3)
    g = Graph("hub", 256, base.edges.union(spark.range(256).selectExpr("id as src", "3L as dst")).distinct())
    width, mass = lay.build(g, 16), lay.build(g, 16, how="mass")
    most = lambda x: x.blocks.groupBy("q").agg(F.sum("xi").alias("m")).agg(F.max("m")).first()[0]
    assert most(mass) <= most(width) and mass.intervals.firsts[0] == 0
    runs = [engine.iterate(x, alg.pagerank_program(g.n), 2).values for x in (width, mass)]
    assert metrics.max_abs_diff(*runs, "rank") < 1e-12 and runs[1].count() == 256


def test_union_find_has_an_exchange_at_every_level(spark):
    g = Graph("chain", 500, spark.range(499).selectExpr("id as src", "id + 1 as dst"))
    found = alg.wcc(g, "unionfind")
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert plan.count("MapInArrow") == plan.count("RoundRobinPartitioning") + plan.count("SinglePartition") > 1 and found.where("label <> 0").count() == 0


def test_dense_path_builds_no_hash_table(spark, sf):
    g = hetero(spark, sf)
    layout, prog = lay.build(g, 64, bucketed=True), alg.pagerank_program(g.n)
    with settings(spark, **engine.PLAN, spark__sql__adaptive__enabled="false"):
        values, _ = engine.generation(layout, engine.start(layout, prog))
        plan = schemes.dense(layout, values, prog)._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "ShuffledHashJoin" not in plan
    assert plan.count("Sort [") <= 1  # of the slices alone: buckets are read as they were sorted
    layout.drop()


def test_two_mode_cost_is_never_above_either(spark):
    rows = simulate.memory_curve(simulate.paper_graphs(spark), [0.25, 1, 4, 8, 16]).collect()
    by = {(r.graph, r.gib, r.scheme): r.tcost for r in rows}
    for g, *_ in simulate.PAPER_GRAPHS:
        for m in (0.25, 1, 4, 8, 16):
            assert by[g, m, "two_mode"] <= min(by[g, m, "dense"], by[g, m, "stream"])
        assert by[g, 0.25, "dense"] >= by[g, 1, "dense"] >= by[g, 16, "dense"] and by[g, 0.25, "stream"] == by[g, 16, "stream"]
