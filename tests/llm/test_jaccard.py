from collections import Counter

import numpy as np
import pytest

from blockgraph.llm import jaccard
from tests.llm import brute
from tests.llm.data import corpus, frame, odd

CLASH = ("node", "n", "doc", "doc_key", "component", "t")


def near_copies(seed, n):
    """Many texts that differ from one of two bases in a few words: some pairs just above, some just below the threshold."""
    r = np.random.default_rng(seed)
    bases = [[f"b{k}w{i}" for i in range(80)] for k in range(2)]
    rows = []
    for i in range(n):
        w = list(bases[int(r.integers(2))])
        for at in r.integers(0, 80, int(r.integers(0, 4))):
            w[at] = f"e{r.integers(10**6)}"
        rows.append((i * 2, " ".join(w)))
    return rows


@pytest.mark.parametrize(("short", "many", "salt", "piece"), [(64, 20, 500, 1000), (3, 20, 2, 1000), (3, 20, 500, 4), (3, 0, 500, 1000)])
def test_join_equals_brute_force(spark, monkeypatch, short, many, salt, piece):
    monkeypatch.setattr(jaccard, "SHORT", short)
    monkeypatch.setattr(jaccard, "MANY", many)
    monkeypatch.setattr(jaccard, "SALT", salt)
    monkeypatch.setattr(jaccard, "PIECE", piece)
    rows = corpus(3) + [(d + 1000, t) for d, t in near_copies(4, 90)]
    got = [tuple(r) for r in jaccard.join(frame(spark, rows, CLASH)).collect()]
    assert Counter(got) == Counter(brute.jaccard_components(rows))
    assert len({c for _, _, c in got}) < len(rows) - 20


def shared_passages(seed, n=70, pool=14, each=6, length=14):
    """Texts made of passages that many texts have, each with a near copy: leaders of lists are at a similarity of 0.2 to 0.5 to most members."""
    r = np.random.default_rng(seed)
    passages = [[f"p{k}w{i}" for i in range(length)] for k in range(pool)]
    rows = []
    for i in range(n):
        w = [x for k in r.choice(pool, each, replace=False) for x in passages[k]]
        rows.append((2 * i, " ".join(w)))
        w[int(r.integers(len(w)))] = f"e{i}"
        rows.append((2 * i + 1, " ".join(w)))
    return rows


@pytest.mark.parametrize(("seed", "piece"), [(1, 1000), (2, 5)])
def test_bounded_distances_to_a_leader_rule_out_no_link(spark, monkeypatch, seed, piece):
    monkeypatch.setattr(jaccard, "SHORT", 3)
    monkeypatch.setattr(jaccard, "PIECE", piece)
    rows = shared_passages(seed)
    got = [tuple(r) for r in jaccard.join(frame(spark, rows)).collect()]
    assert Counter(got) == Counter(brute.jaccard_components(rows))


def test_odd_rows_and_empty_tables(spark):
    rows = odd()
    got = {tuple(r) for r in jaccard.join(frame(spark, rows)).collect()}
    assert (5, 0, 5) in got and (7, 0, 7) in got and (None, 0, None) in got and (3, 15, None) in got and (10, 1, 10) in got
    assert jaccard.join(frame(spark, [])).count() == 0
    kept = jaccard.keep_one(frame(spark, rows, CLASH))
    assert Counter(r.doc_id for r in kept.collect()) == Counter([None, None, 5, 7, 8, 10])
    assert kept.columns[-len(CLASH):] == list(CLASH)


def test_bitmaps_bound_the_difference():
    r = np.random.default_rng(2)
    sets = [np.unique(r.integers(0, 2**63, int(k)).astype(np.uint64)) for k in (5, 200, 900, 3)]
    sets += [np.sort(np.append(s[2:], np.uint64(7))) for s in sets]
    b = jaccard.bitmaps(np.concatenate(sets), np.array([len(s) for s in sets])).view(np.uint64)
    for i, x in enumerate(sets):
        for j, y in enumerate(sets):
            assert sum(int(v).bit_count() for v in b[i] ^ b[j]) <= len(np.setxor1d(x, y))


def test_overlap_bound_is_a_bound():
    r = np.random.default_rng(1)
    for _ in range(300):
        a, b = (np.unique(r.integers(0, 60, int(r.integers(0, 50)))) for _ in range(2))
        both = len(np.intersect1d(a, b))
        assert both <= jaccard.overlap_bound(a, b, 3) <= min(len(a), len(b))
