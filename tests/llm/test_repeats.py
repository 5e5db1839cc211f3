from collections import Counter

import pytest

from blockgraph.llm import repeats, substring_dedup, suffix_dedup
from tests.llm import brute
from tests.llm.data import corpus, frame, odd

CLASH = ("runs", "doc", "h", "s", "n", "want", "seg", "doc_key")


@pytest.mark.parametrize(("hot", "seed"), [("none", 1), ("contents", 2), ("sample", 1)])
def test_suffix_dedup_equals_brute_force(spark, monkeypatch, hot, seed):
    if hot != "none":
        monkeypatch.setattr(repeats, {"contents": "HOT", "sample": "SAMPLE_HOT"}[hot], 0 if hot == "contents" else 1)
    rows = corpus(seed)
    got = [tuple(r) for r in suffix_dedup.digest(frame(spark, rows, CLASH)).collect()]
    assert Counter(got) == Counter(brute.suffix_dedup(rows, 100))
    assert sum(r[2] for r in got) > 5000


@pytest.mark.parametrize(("hot", "seed"), [("none", 1), ("contents", 2), ("sample", 1)])
def test_substring_dedup_equals_brute_force(spark, monkeypatch, hot, seed):
    if hot != "none":
        monkeypatch.setattr(repeats, {"contents": "HOT", "sample": "SAMPLE_HOT"}[hot], 0 if hot == "contents" else 1)
    rows = corpus(seed)
    got = [tuple(r) for r in substring_dedup.digest(frame(spark, rows, CLASH)).collect()]
    assert Counter(got) == Counter(brute.substring_dedup(rows, 13))
    assert sum(r[2] for r in got) > 500


def test_odd_rows_and_empty_tables(spark):
    rows = odd()
    assert Counter(tuple(r) for r in suffix_dedup.digest(frame(spark, rows)).collect() if r[0]) == Counter(r for r in brute.suffix_dedup(rows, 100) if r[0])
    assert Counter(tuple(r) for r in substring_dedup.digest(frame(spark, rows)).collect() if r[0]) == Counter(r for r in brute.substring_dedup(rows, 13) if r[0])
    assert suffix_dedup.digest(frame(spark, [])).count() == substring_dedup.digest(frame(spark, [])).count() == 0
    assert {(r.doc_id, r.n_removed) for r in substring_dedup.digest(frame(spark, rows)).collect() if r.doc_id in (None, 3)} == {(None, 0), (3, 19)}


def test_small_pieces_of_a_long_text(spark, monkeypatch):
    monkeypatch.setattr(repeats, "PIECE", 700)
    rows = corpus(5, n=40)
    import numpy as np

    from blockgraph.llm.text import buffers
    import pyarrow as pa

    x, off = suffix_dedup.RULE.units(pa.array([t for _, t in rows]))
    h, g, doc, s, n = repeats.segments(x, off, 100, 24)
    covered = sorted((d, a + i) for d, a, k in zip(doc.tolist(), s.tolist(), n.tolist()) for i in range(k))
    assert covered == [(d, i) for d, k in enumerate(np.diff(buffers(pa.array([t for _, t in rows]))[1])) for i in range(k - 99)]


def test_texts_are_cut(spark):
    rows = [(1, "é" * 80), (2, "ab" + "é" * 80 + "cd"), (3, None)]
    cut = suffix_dedup.remove(frame(spark, rows, ("runs",)))
    out = {r.doc_id: r for r in cut.collect()}
    assert cut.columns[-1] == "runs" and out[2].runs == "?"
    assert out[3].text is None and out[2].text == "abcd" and out[2].n_chars == 4


def test_rows_of_one_id_are_rows_of_their_own(spark):
    """Null and repeated ids with different texts, each row against plain Python: what repeats nowhere stays."""
    base = [t for _, t in corpus(7, n=60) if t]
    rows = [(None if i % 3 == 0 else i % 5, t) for i, t in enumerate(base)] + [(None, " ".join(f"own{i}" for i in range(90))), (2, base[0]), (2, base[0])]
    df = frame(spark, rows)
    hashes = dict(df.selectExpr("text", "xxhash64(text) as h").distinct().collect())
    got = Counter(tuple(r) for r in suffix_dedup.digest(df).collect())
    assert got == Counter(brute.suffix_dedup(rows, 100, hashes.get))
    got = Counter(tuple(r) for r in substring_dedup.digest(df).collect())
    assert got == Counter(brute.substring_dedup(rows, 13))
    out = suffix_dedup.remove(df)
    assert any(r.text == rows[-3][1] for r in out.collect()) and out.count() == len(rows)


def test_refinement_reuses_buckets_over_several_rounds():
    import numpy as np

    r = np.random.default_rng(4)
    seg = np.frombuffer(bytes(r.choice([97, 98], 40)) * 40, np.uint8)
    off = np.array([0, 700, len(seg)])
    group = np.array([5, 5])
    name = suffix_dedup.window_classes(group, seg, off, 100, 8)
    raw = seg.tobytes()
    by = {}
    for i in [*range(601), *range(700, len(seg) - 99)]:
        assert by.setdefault(raw[i : i + 100], name[i]) == name[i]
    assert len(set(by.values())) == len(by)
