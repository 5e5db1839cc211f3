import math
import random
from collections import Counter

import pytest

from blockgraph.llm import decontaminate as dc
from tests.llm.brute import lower, words
from tests.llm.data import frame


def items_and_rows(seed=1):
    r = random.Random(seed)
    common = [f"the{i}" for i in range(12)]
    word = lambda: r.choice(common) if r.random() < 0.5 else f"w{r.randrange(3000)}"
    items = [(i, " ".join(word() for _ in range(r.choice([6, 12, 18, 33, 50])))) for i in range(30)]
    items += [(90, "a b"), (91, None), (92, ""), (5, items[5][1]), (93, "What is w1 w2 w3 w4?\nIt is w5 w6 w7")]
    rows = []
    for i in range(80):
        t = [word() for _ in range(r.randrange(0, 150))]
        if i % 3 == 0:
            leak = items[i % 30][1].split()
            for _ in range(r.randrange(3)):
                leak[r.randrange(len(leak))] = "changed"
            at = r.randrange(len(t) + 1)
            t[at:at] = leak
        rows.append((i, " ".join(t).upper() if i % 2 else " ".join(t)))
    return items, [*rows, (200, None), (201, ""), (None, items[3][1]), (0, rows[0][1])]


def brute(items, rows):
    """All passages against all items, the sums written out."""
    seen, classes, out = set(), {}, {}
    for i, t in sorted((x for x in items if x[1]), key=lambda x: x[0]):
        w = words(lower(t))
        if (i, t) not in seen and len(w) >= dc.MIN_WORDS:
            seen.add((i, t))
            classes.setdefault(max(16, 2 ** math.ceil(math.log2(len(w)))), []).append((i, t, w))
    trigrams = lambda w: {tuple(w[k : k + min(3, len(w))]) for k in range(len(w) - min(3, len(w)) + 1)}
    every = [x for group in classes.values() for _, _, x in group]
    df, mean = Counter(t for x in every for t in set(x)), sum(map(len, every)) / len(every)
    for row, (_, text) in enumerate(rows):
        w = words(lower(text))
        for span, group in classes.items():
            weight = lambda t, x: math.log(1 + (len(every) - df[t] + 0.5) / (df[t] + 0.5)) * x.count(t) * 2.2 / (x.count(t) + 1.2 * (0.25 + 0.75 * len(x) / mean))
            for at in range(0, max(1, len(w) - span), span):
                piece = w[at : at + 2 * span]
                for i, t, x in group:
                    own = {k: weight(k, x) for k in set(x)}
                    score = sum(own[k] for k in own if k in piece) / sum(own.values())
                    if score >= dc.SCORE - 1e-9:
                        have = trigrams(piece) if piece else set()
                        q, a = (len(p & have) / len(p) if p else 1.0 for p in (trigrams(words(lower(y))) if words(y) else set() for y in dc.question_and_answer(t)))
                        if q >= dc.OVERLAP and a >= dc.OVERLAP:
                            out[row, i] = max(out.get((row, i), (0, 0, 0)), (score, q, a))
    return Counter((rows[row][0], i, *(round(v, 4) for v in x)) for (row, i), x in out.items())


@pytest.mark.parametrize(("postings", "block", "cells"), [(4, 16 << 20, 100), (16, 2000, 4_000_000)])
def test_equals_brute_force(spark, monkeypatch, postings, block, cells):
    for name, value in (("POSTINGS_BLOCK", postings), ("BLOCK_BYTES", block), ("CELLS", cells)):
        monkeypatch.setattr(dc, name, value)
    items, rows = items_and_rows()
    benchmark = spark.createDataFrame(items, "item_id long, text string")
    got = Counter((r[0], r[1], *(round(v, 4) for v in r[2:])) for r in dc.find(frame(spark, rows, ("item_id", "score")), benchmark).collect())
    assert got == brute(items, rows) and sum(got.values()) > 20
    leaks = {t for d, t in rows for x in got if x[0] == d and d != 0 and d is not None} | {items[3][1]} | {t for d, t in rows if d == 0 and any(x[0] == 0 for x in got)}
    kept = dc.remove(frame(spark, [*rows, (None, "clean words only")], ("doc_key",)), benchmark)
    assert Counter((r.doc_id, r.text) for r in kept.collect()) == Counter((d, t) for d, t in [*rows, (None, "clean words only")] if t not in leaks)
    assert kept.columns[-1] == "doc_key"


def test_index_grows_with_the_postings():
    r = random.Random(5)
    sizes = []
    for n in (500, 1000, 2000):
        items = [(i, dc._hashes(" ".join(f"t{int(r.paretovariate(0.7)) % 20_000}" for _ in range(20)))) for i in range(n)]
        index = dc.Index(items, 32)
        postings = sum(len(set(h.tolist())) for _, h in items)
        assert len(index.range_most) == len(index.range_of) <= postings == len(index.items)
        sizes.append(sum(x.nbytes for x in (index.item, index.weight, index.range_most, index.range_of, index.range_start, index.vocabulary)) / postings)
    assert max(sizes) < 1.5 * min(sizes)


def test_items_of_few_words_count_as_whole_sequences(spark):
    benchmark = spark.createDataFrame([(1, "Blue whale"), (2, "x"), (3, "one two\nthree four"), (4, "blue WHALE"), (5, " ")], "item_id long, text string")
    rows = [(1, "a blue whale swims"), (2, "whale blue"), (3, "blue"), (4, "whale X"), (5, "zero one two three four"), (6, "one two three"), (7, "four"), (8, None)]
    assert sorted(tuple(r) for r in dc.find(frame(spark, rows), benchmark).collect()) == [(1, 1, 1.0, 1.0, 1.0), (1, 4, 1.0, 1.0, 1.0), (4, 2, 1.0, 1.0, 1.0), (5, 3, 1.0, 1.0, 1.0)]


def test_search_equals_sums():
    r = random.Random(3)
    items = [(i, dc._hashes(" ".join(f"t{int(r.paretovariate(0.6)) % 60}" for _ in range(r.randrange(5, 30))))) for i in range(150)]
    index = dc.Index(items, 32)
    for _ in range(200):
        terms = sorted(r.sample(range(len(index.vocabulary)), r.randrange(1, min(25, len(index.vocabulary)))))
        sums = Counter()
        for t in terms:
            for p in range(index.start[t], index.start[t + 1]):
                sums[int(index.item[p])] += float(index.weight[p])
        for threshold in (0.1, 0.3, 0.5):
            got = index.search(terms, threshold)
            assert {i for i, _ in got} == {i for i, s in sums.items() if s >= threshold - 1e-9}
            assert all(abs(s - sums[i]) < 1e-9 for i, s in got)


def test_empty_tables(spark):
    none = spark.createDataFrame([], "item_id long, text string")
    assert dc.find(frame(spark, [(1, "a b c d e f")]), none).count() == 0
    assert dc.find(frame(spark, []), spark.createDataFrame([(1, "a b c d e f")], "item_id long, text string")).count() == 0
