"""The driver's contract, some keys against DuckDB, and life without the llm folders."""

import os
import shutil
import subprocess
import sys

import pytest

import __spark_entry__ as entry
from tests.oracle_check import compare, connect

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
KEYS = ["layout_beta", "layout_modes_hetero", "criterion_equivalence", "zigzag_loads", "tcost_memory_paper", "crossover", "join_asof", "join_interval", "join_range_interval", "agg_cube_blocks", "fn_array_hof", "stream_late", "udtf_rmat", "src_adjacency", "rwr_purchase", "wcc_iter1_hetero", "triangles_exact", "network_rows"]


def test_every_sql_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries()) and len(entry.queries()) > 180


def test_entry(spark):
    assert entry.entry(spark).count() == 1890


@pytest.mark.parametrize("key", KEYS)
def test_key_equals_sql(spark, sf, key):
    assert compare(entry.queries()[key], entry.oracle_sql()[key], spark, connect(sf), sf).startswith("ok")


def test_without_llm(tmp_path):
    shutil.copytree(ROOT, tmp_path / "r", ignore=shutil.ignore_patterns(".git", "__pycache__", "llm", "corpus_pipeline.py", "spark-warehouse"))
    code = "import __spark_entry__ as e; q = e.queries(); assert 'pagerank_hetero' in q and not any(k.startswith('op') for k in q)"
    there = os.environ | {"PYTHONPATH": str(tmp_path / "r")}
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path / "r", check=True, timeout=120, env=there)
    some = ["tests/test_core.py::test_toy_blocks_and_zigzag", "tests/test_hops.py", "tests/test_entry.py::test_every_sql_has_a_query", "tests/test_entry.py::test_entry"]
    subprocess.run([sys.executable, "-m", "pytest", "-q", "-x", "-p", "no:cacheprovider", *some], cwd=tmp_path / "r", check=True, timeout=400, env=there)


def test_a_missing_dependency_is_an_error(tmp_path):
    shutil.copytree(ROOT, tmp_path / "r", ignore=shutil.ignore_patterns(".git", "__pycache__", "spark-warehouse"))
    code = "import sys; sys.modules['public_package'] = None; import __spark_entry__"
    (tmp_path / "r" / "corpus_pipeline.py").write_text("import public_package\n")
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path / "r", timeout=120, env=os.environ | {"PYTHONPATH": str(tmp_path / "r")}, capture_output=True)
    assert done.returncode and b"public_package" in done.stderr
