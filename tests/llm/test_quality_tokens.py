import numpy as np
import pytest

from blockgraph.llm import quality, tokens
from blockgraph.llm.queries import vocabulary_path
from tests.llm.data import corpus, frame, odd


def test_counts_equal_the_library(spark, sf):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(vocabulary_path())
    tricky = ["<|endoftext|>", "a<|endoftext|><|endoftext|> b", "  two  spaces\n\n\tx ", "don't I'LL we've", "１２３ ٣ x²", "é 日本語 😀👍🏽", " nbsp em", "a" * 5000, " " * 300, "\x00\x1f", "ſ K", "<|endoftext|", "don’t"]
    rows = corpus(7) + odd() + list(enumerate(tricky, 5000))
    rows += [(r.doc_id + 9000, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    got = sorted((tuple(r) for r in tokens.count_tokens(frame(spark, rows, ("n_tokens", "n_bytes")), vocabulary_path()).collect()), key=str)
    want = sorted(((d, len((x or "").encode()), n := len(t.encode(x or "", add_special_tokens=False).ids), n > 512) for d, x in rows), key=str)
    assert got == want
    assert tokens.count_tokens(frame(spark, []), vocabulary_path()).count() == 0


def test_second_tier_stays_bounded(monkeypatch):
    monkeypatch.setattr(tokens, "CACHE_SIZE", 3)
    c = tokens.Cache(len, {"a": 1})
    assert [c[x] for x in ("bb", "ccc", "dddd", "eeeee", "ffffff", "a")] == [2, 3, 4, 5, 6, 1] and len(c) <= 4


def test_held_out_quality(spark):
    sf = "/root/testdata/sf0.01"
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    out = quality.classify(spark.read.parquet(f"{sf}/documents.parquet"), labels).join(labels, "doc_id").where("held_out").toPandas()
    good, bad = out[out.quality == 1].score.to_numpy(), out[out.quality == 0].score.to_numpy()
    assert (good[:, None] > bad[None]).mean() > 0.97 and (out.predicted == out.quality).mean() > 0.93


def test_updates_equal_the_textbook_form():
    """One coordinate at a time, the closed form of the regularised leader."""
    r = np.random.default_rng(1)
    model, z, n = quality.Ftrl(4), np.zeros(4), np.zeros(4)
    for _ in range(50):
        x, y = r.random(4), int(r.integers(2))
        w = np.array([0.0 if abs(a) <= quality.L1 else -(a - np.sign(a) * quality.L1) / ((quality.BETA + b**0.5) / quality.ALPHA + quality.L2) for a, b in zip(z, n)])
        p = 1 / (1 + np.exp(-w @ x))
        for i in range(4):
            g = (p - y) * x[i]
            z[i] += g - ((n[i] + g * g) ** 0.5 - n[i] ** 0.5) / quality.ALPHA * w[i]
            n[i] += g * g
        assert abs(model.update(np.arange(4), x, y) - p) < 1e-12
    assert np.allclose(model.z, z)


def test_odd_rows(spark):
    docs = frame(spark, odd(), ("score", "predicted"))
    labels = spark.createDataFrame([(3, 1, 0), (3, 0, 0), (None, 1, 0), (8, None, None), (99, 1, 1), (10, 0, 0)], "doc_id long, quality int, toxic int")
    out = quality.classify(docs, labels).collect()
    assert len(out) == len(odd()) and all(0 <= r.score <= 1 for r in out)
    nothing = np.zeros(2**quality.BITS + 1, np.float32)
    empty = quality.score(docs, nothing, names=("p", "good"))
    assert {(r.p, r.score) for r in empty.collect()} == {(0.5, "?")} and empty.columns == [*docs.columns, "p", "good"]
    assert quality.keep_good(docs, nothing).columns == docs.columns and quality.keep_good(docs, nothing).count() == len(odd())
    with pytest.raises(ValueError, match="columns"):
        quality.score(docs, nothing)
    assert quality.classify(docs.limit(0), labels.limit(0)).count() == 0


@pytest.mark.parametrize("n", [0, 1, 2, 3])
def test_features_stay_inside_their_text(n):
    import pyarrow as pa

    from blockgraph.llm.text import buffers

    texts = ["w1 w2 w3", "", None, "w9", "Ab!! cd ef"]
    at, k = quality.features(*buffers(pa.array(texts)))
    ends = np.cumsum(k)
    for i, t in enumerate(texts):
        alone, m = quality.features(*buffers(pa.array([t], pa.string())))
        assert m[0] == k[i] and (alone == at[ends[i] - k[i] : ends[i]]).all()
