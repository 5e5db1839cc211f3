"""Neighbourhoods grow until nothing is new."""

import pytest

from blockgraph.operators import algorithms as alg
from blockgraph.sources.graphs import Graph


def path(spark, n):
    return Graph("path", n, spark.createDataFrame([(i, i + 1) for i in range(n - 1)], "src long, dst long"))


def test_hops_are_not_capped(spark):
    n = 67
    got = {r.hops: r.pairs for r in alg.neighbourhood_exact(path(spark, n)).collect()}
    assert got == {h: sum(n - k for k in range(h + 1)) for h in range(n)}


def test_a_reached_limit_is_an_error(spark):
    with pytest.raises(RuntimeError):
        alg.neighbourhood_exact(path(spark, 6), 3)
    with pytest.raises(RuntimeError):
        alg.neighbourhood_sketch(path(spark, 40), max_hops=2, beta=2)


def test_sketches_of_few_ids_are_not_biased(spark):
    assert [alg.estimated_ids(z) for z in (0, 0.5, 1)] == [0, 1, 2]
    assert all(abs(alg.estimated_ids(alg._ZEROS[-1] + d) / alg.estimated_ids(alg._ZEROS[-1] - d) - 1) < 0.01 for d in (1e-6, 1e-3))
    g = Graph("alone", 3000, spark.createDataFrame([(0, 1)], "src long, dst long"))
    assert abs(alg.neighbourhood_sketch(g, registers=32)[0][1] / 3000 - 1) < 0.05
