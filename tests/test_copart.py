"""Triangles and components of the whole co-purchase graph, against brute force on all pairs of lines."""

from itertools import combinations

import duckdb

import __spark_entry__ as entry


def test_triangles_and_components_of_all_lines(spark, sf):
    near, orders = {}, {}
    for o, p in duckdb.sql(f"SELECT DISTINCT l_orderkey, l_partkey FROM '{sf}/lineitem.parquet'").fetchall():
        orders.setdefault(o, []).append(p)
    for parts in orders.values():
        for a, b in combinations(parts, 2):
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
    want = sum(len({c for c in near[a] & near[b] if c > b}) for a in near for b in near[a] if b > a)
    assert [r[0] for r in entry.queries()["triangles_copart"](spark, sf).collect()] == [want] and want > 0
    label = {r.id: r.label for r in entry.queries()["wcc_unionfind_copart"](spark, sf).collect()}
    seen = {}
    for v in sorted(label):
        if v not in seen:
            todo = [v]
            while todo:
                x = todo.pop()
                if x not in seen:
                    seen[x] = v
                    todo += near.get(x, ())
    assert label == seen
