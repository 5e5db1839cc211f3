"""Every stage against a plain version on its own input, and the whole on the smallest tables."""

from collections import Counter

import corpus_pipeline as cp
from blockgraph.llm import quality
from tests.llm import brute
from tests.llm.data import corpus, frame, odd


def keys(df):
    return Counter((r.doc_id, r.text) for r in df.collect())


def test_near_duplicates_and_repeats(spark, sf):
    rows = corpus(11, n=90)
    docs = frame(spark, rows)
    kept = cp.without_near_duplicates(spark, docs, sf)
    label = {d: c for d, _, c in brute.jaccard_components(rows)}
    assert kept.columns == docs.columns and keys(kept) == Counter((d, t) for d, t in rows if label[d] == d)
    cut = cp.without_repeats(spark, docs, sf)
    assert cut.columns == docs.columns
    lost = {r[0]: r[2] for r in brute.suffix_dedup(rows, 100)}
    for r in cut.collect():
        whole = dict(rows)[r.doc_id]
        assert (r.text is None) == (whole is None) and r.n_chars == (len(r.text) if r.text is not None else None)
        assert len((r.text or "").encode()) <= len((whole or "").encode()) - lost[r.doc_id]
        if not lost[r.doc_id]:
            assert r.text == whole


def test_quality_and_leaks(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = cp.classified(spark, docs, sf)
    scored = quality.classify(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {r.doc_id for r in scored.where("predicted = 1").collect()}
    items = [r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    clean = {r.doc_id for r in cp.without_leaks(spark, docs, sf).collect()}
    assert {r.doc_id for r in docs.collect() if not any(t in r.text for t in items)} == clean


def test_whole_pipeline(spark, sf):
    out = cp.run(spark, sf).collect()
    assert 50 < len(out) < 200 and all(r.taken <= 3 * r.size for r in out)
    assert [n for n, _ in cp.STAGES] == ["quality", "near-duplicates", "repeats", "leaks", "mix"]


def test_stages_take_odd_rows(spark, sf):
    docs = frame(spark, odd())
    for _, stage in cp.STAGES:
        assert stage(spark, docs, sf).count() >= 0 and stage(spark, docs.limit(0), sf).count() == 0
