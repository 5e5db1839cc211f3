"""Keys over whole tables."""

import pytest

import __spark_entry__ as entry
from tests.oracle_check import compare, connect


@pytest.mark.parametrize("key", ["fn_cosine_knn", "edges_filtered"])
def test_no_ids_are_left_out(spark, sf, key):
    assert compare(entry.queries()[key], entry.oracle_sql()[key], spark, connect(sf), sf).startswith("ok")
    out = entry.queries()[key](spark, sf)
    if key == "fn_cosine_knn":
        assert out.count() == 10 * spark.read.parquet(f"{sf}/embeddings.parquet").count()
    else:
        assert out.where("src > 5").count() > 0
