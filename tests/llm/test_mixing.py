from fractions import Fraction

import duckdb
import pytest

from blockgraph.llm import mixing
from tests.llm.data import corpus, frame, odd


def brute_targets(sizes, epochs):
    """The clamping written out: shares by weight, what is above the limit goes to the others, until none is above."""
    names = sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else [])
    weight = {s: i % 3 + 1 for i, s in enumerate(names)}
    target, free, rest = {}, set(names), Fraction(sum(sizes.values()))
    while True:
        total = sum(weight[s] for s in free)
        over = [s for s in free if rest * weight[s] / total > epochs * sizes[s]] if free else []
        if not over:
            return target | {s: rest * weight[s] / total for s in free}
        for s in over:
            target[s] = Fraction(epochs * sizes[s])
            free.discard(s)
            rest -= target[s]


@pytest.mark.parametrize("rows", ["corpus", "odd", "skewed"])
def test_targets_and_takings(spark, rows):
    data = {"corpus": corpus(4), "odd": odd(), "skewed": [(i, "w " * (1 if i % 3 else 900)) for i in range(90)]}[rows]
    df = frame(spark, data, ("size", "target", "bin"))
    out = mixing.mix(df).collect()
    assert len(out) == len(data)
    sizes, taken, target = {}, {}, {}
    for r in out:
        sizes[r.source] = sizes.get(r.source, 0) + r.size
        taken[r.source] = taken.get(r.source, 0) + r.taken
        target[r.source] = r.target
        assert 0 <= r.taken <= 3 * r.size
    for s, want in brute_targets(sizes, 3).items():
        assert abs(target[s] - float(want)) < 1e-6 and abs(taken[s] - target[s]) <= 0.5 + 1e-6
    assert sorted(map(tuple, out), key=str) == sorted(map(tuple, mixing.mix(df).collect()), key=str)


def test_equals_sql(spark):
    data = corpus(5) + odd()
    df = frame(spark, data).toPandas()  # noqa: F841  (read by DuckDB)
    got = sorted((tuple(r) for r in mixing.mix(frame(spark, data)).select("doc_id", "size", "source_size", "target", "taken").collect()), key=str)
    con = duckdb.connect()
    con.register("docs", df.astype({"doc_id": "Int64"}))
    assert sorted((tuple(r) for r in con.sql(mixing.MIX_SQL.format(docs="docs")).fetchall()), key=str) == got


def test_carried_columns_stay_with_their_rows(spark):
    data = corpus(5) + odd()
    got = mixing.mix(frame(spark, data), carry=("text", "n_chars"))
    assert sorted(((r.doc_id, r.text, r.n_chars) for r in got.collect()), key=str) == sorted(((d, t, None if t is None else len(t)) for d, t in data), key=str)
    with pytest.raises(ValueError, match="size"):
        mixing.mix(frame(spark, data, ("size",)), carry=("size",))


def test_empty_and_wordless(spark):
    assert mixing.mix(frame(spark, [])).count() == 0
    assert [(r.target, r.taken) for r in mixing.mix(frame(spark, [(1, ""), (2, None)])).collect()] == [(0.0, 0)] * 2
