"""Triangles by pairs of colours: against brute force for any number of colours, and on disk no more than the edges."""

import os
from itertools import combinations

import numpy as np
import pytest

from blockgraph.operators import algorithms as alg
from blockgraph.operators import triangles as tri
from blockgraph.sources.graphs import GRAPHS, Graph
from blockgraph.storage import settings


@pytest.mark.parametrize("per_task", [10**6, 300, 90])
def test_any_number_of_colours(spark, monkeypatch, per_task):
    """Hubs, loops, edges in one or both directions or twice, ids that are far apart."""
    r = np.random.default_rng(3)
    rows = [(int(a) ** 7, int(b) ** 7) for a, b in r.integers(0, 60, (500, 2))] + [(0, i**7) for i in range(60)] + [(i**7, 1) for i in range(60)]
    rows += [(b, a) for a, b in rows[::3]] + rows[:9]
    near = {}
    for a, b in rows:
        if a != b:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
    want = sum(b in near[a] and c in near[a] and c in near[b] for a, b, c in combinations(sorted(near), 3))
    assert (tri.colours(sum(map(len, near.values())) // 2, per_task) == 1) == (per_task == 10**6)
    monkeypatch.setattr(tri, "PER_TASK", per_task)
    got = alg.triangles(Graph("g", 60**7, spark.createDataFrame(rows, "src long, dst long")))
    assert got.dtypes == [("triangles", "bigint")] and [x[0] for x in got.collect()] == [want] and want > 0


def test_without_edges_or_triangles(spark):
    for rows in ([], [(1, 1)], [(0, 1)], [(i, i + 1) for i in range(9)]):
        assert alg.triangles(Graph("g", 10, spark.createDataFrame(rows, "src long, dst long"))).collect() == [(0,)]


def test_packed_edges_come_back():
    a, b = np.sort(np.array([-5, 0, 2**62, 7, 7])), np.array([2**40, -1, 3, 0, 2**63 - 1])
    for got, want in zip(tri.unpack(tri.pack(a, b)), (a, b), strict=True):
        assert (got == want).all()


def test_pairs_of_neighbours_are_not_exchanged(spark):
    """300 vertices that all meet: 44,850 edges and 4,455,100 pairs of neighbours, of which none is on disk."""
    n = 300
    dirs = [str(d) for d in spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirs()]
    held = lambda: {f: os.path.getsize(f) for d in dirs for at, _, names in os.walk(d) for f in (os.path.join(at, x) for x in names) if os.path.exists(f)}
    ids = spark.range(n)
    clique = Graph("clique", n, ids.withColumnRenamed("id", "src").crossJoin(ids.withColumnRenamed("id", "dst")).where("src < dst"))
    before = held()
    with settings(spark, spark__sql__autoBroadcastJoinThreshold="-1"):  # as with tables too large for it
        assert alg.triangles(clique).first()[0] == n * (n - 1) * (n - 2) // 6
    assert sum(v for f, v in held().items() if f not in before) < 40 * n * n / 2


def test_copart_is_counted_in_one_direction(spark, sf):
    g = GRAPHS["copart"](spark, sf)
    edges = {(x.src, x.dst): x.w for x in g.edges.collect()}
    assert {(x.src, x.dst): x.w for x in g.half.collect()} == {e: w for e, w in edges.items() if e[0] < e[1]}
    assert len(edges) == g.edges.count() and all(edges[b, a] == w for (a, b), w in edges.items())
    both = g.symmetric()
    assert {(x.src, x.dst): x.w for x in both.edges.collect()} == edges and both.weighted
