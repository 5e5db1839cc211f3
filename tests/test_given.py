"""Cost keys and the generator source work on the given tables."""

import pytest

import __spark_entry__ as entry
from tests.oracle_check import compare, connect


@pytest.mark.parametrize("key", ["beta_by_memory", "cost_graph_dense", "cost_graph_stream", "cost_transfers_seeks", "criterion_equivalence", "crossover", "datasource_rmat", "layout_beta"])
def test_a_table_is_read(spark, sf, key):
    assert entry.queries()[key](spark, sf).inputFiles()
    assert compare(entry.queries()[key], entry.oracle_sql()[key], spark, connect(sf), sf).startswith("ok")
