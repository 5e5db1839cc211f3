import math
import zlib
from collections import Counter

import numpy as np
import pytest

from blockgraph.llm import bloom_lm as lm
from tests.llm.brute import lower, words
from tests.llm.data import corpus, frame, odd


@pytest.fixture(autouse=True)
def few_parts(monkeypatch):
    monkeypatch.setattr(lm, "LEAST_PARTS", 4)


def brute_base(rows):
    toks = [words(lower(t)) + [None] for _, t in rows]
    held = [zlib.crc32(("" if d is None else str(d)).encode()) % 5 == 1 for d, _ in rows]
    c = Counter(x for t, h in zip(toks, held, strict=True) if not h for x in t)
    n, v = sum(c.values()), len(c)
    return sorted((d is not None, d or 0, h, len(t), sum(c[x] > 0 for x in t), n, round(sum(math.log10((c[x] + 0.5) / (n + 0.5 * (v + 1))) for x in t), 6)) for (d, _), t, h in zip(rows, toks, held, strict=True))


def test_base_is_exact_and_the_model_beats_it_where_texts_repeat(spark, monkeypatch):
    rows = corpus(6, n=200, vocabulary=20) + odd()
    for block in (lm.BLOCK_BYTES, 3000):
        monkeypatch.setattr(lm, "BLOCK_BYTES", block)
        out = lm.score(frame(spark, rows, ("row", "token", "count", "held_out"))).collect()
        assert sorted((r.doc_id is not None, r.doc_id or 0, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6)) for r in out) == brute_base(rows)
    held = [r for r in out if r.held_out and r.n_tokens > 20]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)


def test_levels_come_back():
    counts = np.arange(1, 4000)
    up = lm.level(counts)
    assert (lm.lower_end(up) <= counts).all() and (counts <= lm.upper_end(up)).all() and lm.level(np.array([0]))[0] == 0
    h = np.random.default_rng(1).integers(1, 2**63, 3000).astype(np.uint64)
    want = np.arange(3000) % 30 + 1
    f = lm.Slice(int(want.sum()) * lm.BITS_PER_ENTRY)
    f.store(h, want)
    got = f.levels(h)
    assert (got >= want).all() and (got > want).mean() < 0.05
    assert f.holds(np.random.default_rng(2).integers(1, 2**63, 20000).astype(np.uint64), 1).mean() < 0.02


def learnt(rows):
    """Counts of words and pairs of the training rows, in plain Python, and the tokens of every row."""
    toks = [[*words(lower(t)), None] for _, t in rows]
    pairs = [list(zip([None, *t], t, strict=False)) for t in toks]
    train = [zlib.crc32(("" if d is None else str(d)).encode()) % 5 != 1 for d, _ in rows]
    return *(Counter(x for t, h in zip(y, train, strict=True) if h for x in t) for y in (toks, pairs)), pairs


def test_probabilities_of_a_history_add_up_to_one_at_most():
    tables = [learnt(corpus(8, n=60, vocabulary=3))[:2]]
    for k in (4, 8, 12):  # all words equally often, in a ring
        tables.append((Counter({i: k for i in range(1000)}), Counter({(i, (i + 1) % 1000): k for i in range(1000)})))
    for one, two in tables:
        names = list(one)
        word = lm.level(np.array([one[w] for w in names]))
        whole = lm.mass(np.bincount(word, minlength=lm.LEVELS + 1))
        for v in names[:50]:
            pair, history = lm.level(np.array([two[v, w] for w in names])), lm.level(np.array([one[v]]))
            known = lm.smoothed(pair, history, word, whole).sum()
            assert known + lm.smoothed(np.array([0]), history, np.array([0]), whole)[0] <= 1 + 1e-9


def test_scores_use_every_ngram_of_any_corpus(spark, monkeypatch):
    """Against counts in plain Python, those of one occurrence too."""
    rows = corpus(11, n=60, vocabulary=15) + odd()
    one, two, pairs = learnt(rows)
    at = lambda c: lm.level(np.array([c]))
    whole = lm.mass(np.bincount([int(at(c)[0]) for c in one.values()], minlength=lm.LEVELS + 1))
    want = sorted((len(t), round(sum(math.log10(lm.smoothed(at(two[v, w]), at(one[v]), at(one[w]), whole)[0]) for v, w in t), 6)) for t in pairs)
    monkeypatch.setattr(lm, "BITS_PER_ENTRY", 64)  # hardly a false positive
    monkeypatch.setattr(lm, "LEAST_BITS", 1 << 23)
    for block, part in ((lm.BLOCK_BYTES, lm.PART_TOKENS), (2000, 9000)):
        monkeypatch.setattr(lm, "BLOCK_BYTES", block)
        monkeypatch.setattr(lm, "PART_TOKENS", part)
        assert sorted((r.n_tokens, round(r.score, 6)) for r in lm.score(frame(spark, rows)).collect()) == want
    monkeypatch.undo()
    monkeypatch.setattr(lm, "LEAST_PARTS", 4)
    got = [r.score for r in lm.score(frame(spark, rows)).collect()]
    assert abs(sum(got) / sum(s for _, s in want) - 1) < 0.02


def test_empty_table_and_own_split(spark):
    assert lm.score(frame(spark, [])).count() == 0
    assert [tuple(r)[1:5] for r in lm.score(frame(spark, [(1, "a b")])).collect()] in ([(False, 3, 3, 3)], [(True, 3, 0, 0)])
    out = {r.doc_id: r for r in lm.score(frame(spark, [(1, "a b"), (2, "a c")]), lm.F.col("doc_id") == 2).collect()}
    assert (out[2].held_out, out[2].train_tokens, out[2].n_known, out[1].n_known) == (True, 3, 2, 3)
