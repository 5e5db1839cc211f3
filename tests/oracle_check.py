"""python -m tests.oracle_check SF_DIR [KEY...]: every query against its DuckDB SQL, as rows and as value hashes of sorted columns."""

from __future__ import annotations

import decimal
import sys
import time
from collections import Counter

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf: str):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def value(x):
    if isinstance(x, bool) or x is None:
        return x
    if isinstance(x, decimal.Decimal):
        return float(x)
    if isinstance(x, float):
        return 0.0 if x == 0 else x
    if isinstance(x, (list, tuple)):
        return tuple(value(v) for v in x)
    if isinstance(x, dict):
        return tuple(sorted((k, value(v)) for k, v in x.items()))
    return str(x) if hasattr(x, "isoformat") else x


def compare(query, sql: str | None, spark, con, sf: str) -> str:
    df = query(spark, sf)
    names = sorted(df.columns)
    got = Counter(tuple(value(v) for v in r) for r in df.select(*names).toLocalIterator())
    if not sql:
        return f"rows only: {sum(got.values())}"
    rel = con.sql(sql)
    if sorted(rel.columns) != names:
        return f"DIFFERS: columns {names} and {sorted(rel.columns)}"
    at = [rel.columns.index(n) for n in names]
    want = Counter(tuple(value(r[i]) for i in at) for r in rel.fetchall())
    if got == want:
        return f"ok {sum(got.values())}"
    return f"DIFFERS: {sum(got.values())} rows and {sum(want.values())}; only here {list((got - want).items())[:2]}; only there {list((want - got).items())[:2]}"


def main(sf: str, keys: list[str]) -> int:
    from pyspark.sql import SparkSession

    import __spark_entry__ as entry

    spark = SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.driver.memory", "6g").config("spark.sql.session.timeZone", "UTC").config("spark.sql.warehouse.dir", "/tmp/oracle-warehouse").getOrCreate()
    spark.sparkContext.setLogLevel("OFF")
    con, bad = connect(sf), 0
    queries, sql = entry.queries(), entry.oracle_sql()
    for k in keys or queries:
        began = time.time()
        try:
            said = compare(queries[k], sql.get(k), spark, con, sf)
        except Exception as e:  # a broken key is one line, the others go on
            said = f"FAILED: {str(e).strip()[:600]}"
        bad += said.startswith(("DIFFERS", "FAILED"))
        print(f"{k}: {said} ({time.time() - began:.1f} s)", flush=True)
    print(f"{bad} bad")
    return bad


if __name__ == "__main__":
    sys.exit(main(sys.argv[1], sys.argv[2:]))
