"""Benchmark decontamination: BM25 inverted indexes of the test items, block-max WAND over every passage of every text.

Items are indexed by length class (up to 16, 32, 64 ... words). A class of up to S words is asked with every passage of 2 S
words, starting at every S-th word, so each stretch of S words lies whole in some passage. An item's score for a passage is
its BM25 score as a share of the score it gets from its own text; all items of at least ``SCORE`` are retrieved.

Most passages cannot reach the threshold, and most items cannot for a given passage. Items stand in ranges of ``RANGE``; for
each range a term has the largest of its weights there (a list as long as its postings at most). A passage is two stretches of S
words, and the sums of these maxima over a stretch's distinct terms, added up, bound what any item of a range can get. A passage
with no range that can reach the threshold is passed over (passages of a block of texts together, ``CELLS`` sums at a time); the rest is answered exactly by
WAND, which leaves out whole blocks of posting lists by their maxima.

How often a term occurs and how long items are is counted over all items. A retrieved item counts if the passage holds enough of the word
trigrams of both its question and its answer (the last line of several, else the last third of the words). Items under ``MIN_WORDS``
words count where a text holds all their words in a row. The index is broadcast; it is as large as the items' postings, and items
are taken in blocks of at most ``BLOCK_BYTES`` of text, so its size has a bound; texts are read once for each block.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockgraph.llm import text as tx

SCORE, OVERLAP = 0.5, 0.5
K1, B = 1.2, 0.75
GRAM = 3
MIN_WORDS = 5
BLOCK_BYTES = 16 << 20
POSTINGS_BLOCK = 16
SMALLEST_CLASS = 16
RANGE = 2
CELLS = 1_000_000
SCHEMA = "doc_id long, item_id long, score double, question_overlap double, answer_overlap double"
_WORD = re.compile(r"[^\x20\x09-\x0D]+")


def _hashes(text: str) -> np.ndarray:
    buf, off = tx.buffers(pa.array([text]))
    return tx.Words(buf, off).hashes(lower=True)


def question_and_answer(text: str) -> tuple[str, str]:
    """The last of several lines is the answer; of one line, the last third of its words."""
    lines = [x for x in text.split("\n") if _WORD.search(x)]
    if len(lines) > 1:
        return "\n".join(lines[:-1]), lines[-1]
    words = _WORD.findall(text)
    cut = len(words) - max(1, len(words) // 3)
    return " ".join(words[:cut]), " ".join(words[cut:])


def _trigrams(h: np.ndarray) -> np.ndarray:
    return np.unique(tx.grams(h, min(GRAM, max(1, len(h)))))


class Counts:
    """Over a set of items: how many there are, their mean length, and in how many each term occurs."""

    def __init__(self, items: int, words: int, terms: np.ndarray, df: np.ndarray):
        self.items, self.mean, self.terms, self.df = items, words / max(items, 1), terms, df

    @classmethod
    def of(cls, items: list[np.ndarray]) -> "Counts":
        terms, df = np.unique(np.concatenate([np.unique(h) for h in items]) if items else np.zeros(0, np.uint64), return_counts=True)
        return cls(len(items), sum(map(len, items)), terms, df)


class Index:
    """BM25 weights of items, as shares of each item's own score, in posting lists of blocks with maxima."""

    def __init__(self, items: list[tuple[int, np.ndarray]], span: int, score: float = SCORE, told: "Counts | None" = None):
        """told: occurrences and lengths over all items; of these alone if not given."""
        told = told or Counts.of([h for _, h in items])
        self.span, self.score, self.names, self.block, self.cells = span, score, [i for i, _ in items], POSTINGS_BLOCK, CELLS
        sizes = np.array([len(h) for _, h in items], float)
        counted = [np.unique(h, return_counts=True) for _, h in items]
        self.vocabulary = np.unique(np.concatenate([t for t, _ in counted]))
        terms = [np.searchsorted(self.vocabulary, t) for t, _ in counted]
        df = told.df[np.searchsorted(told.terms, self.vocabulary)]
        idf = np.log1p((told.items - df + 0.5) / (df + 0.5))
        rows = []
        for k, (t, (_, tf)) in enumerate(zip(terms, counted, strict=True)):
            w = idf[t] * tf * (K1 + 1) / (tf + K1 * (1 - B + B * sizes[k] / told.mean))
            rows.append(w / w.sum())
        term, item, weight = np.concatenate(terms), np.repeat(np.arange(len(items)), [len(t) for t in terms]), np.concatenate(rows)
        order = np.lexsort((item, term))
        self.item, self.weight = item[order], weight[order]
        self.items, self.weights = self.item.tolist(), self.weight.tolist()
        self.start = np.searchsorted(term[order], np.arange(len(self.vocabulary) + 1))
        self.most = np.maximum.reduceat(self.weight, self.start[:-1]).tolist()
        self.block_most, self.block_last = [], []
        for t in range(len(self.vocabulary)):
            lo, hi = self.start[t], self.start[t + 1]
            cuts = np.arange(lo, hi, self.block)
            self.block_most.append(np.maximum.reduceat(self.weight[lo:hi], cuts - lo).tolist())
            self.block_last.append(self.item[np.minimum(cuts + self.block, hi) - 1].tolist())
        self.ranges = -(-len(items) // RANGE)
        at = term[order] * self.ranges + self.item // RANGE  # ascending
        head = np.flatnonzero(np.append(True, at[1:] != at[:-1]))
        self.range_most, self.range_of = np.maximum.reduceat(self.weight, head), self.item[head] // RANGE
        self.range_start = np.searchsorted(term[order][head], np.arange(len(self.vocabulary) + 1))

    def reachable(self, stretch: np.ndarray, term: np.ndarray, last: np.ndarray, score: float) -> np.ndarray:
        """For every stretch whether some range's bound for it and the next one (none after a text's last) reaches the score.

        stretch, term: the known words, ascending by stretch. No more than about CELLS sums exist at a time."""
        pairs = np.unique(stretch * len(self.vocabulary) + term)
        of, term = np.divmod(pairs, len(self.vocabulary))
        out = np.zeros(len(last), bool)
        step = max(2, self.cells // self.ranges)
        for lo in range(0, len(last), step - 1):  # a stretch's next one is in the same part, or a text ends there
            hi = min(lo + step, len(last))
            a, b = np.searchsorted(of, (lo, hi))
            sums = np.zeros((hi - lo) * self.ranges)
            for c in self._parts(term[a:b]):
                o, t = of[a:b][c] - lo, term[a:b][c]
                many = self.range_start[t + 1] - self.range_start[t]
                at = np.repeat(self.range_start[t] - np.cumsum(many) + many, many) + np.arange(many.sum())
                sums += np.bincount(np.repeat(o, many) * self.ranges + self.range_of[at], self.range_most[at], len(sums))
            sums = sums.reshape(hi - lo, self.ranges)
            sums[:-1] += np.where(last[lo : hi - 1, None], 0, sums[1:])  # rows are read before they change: each adds its old next one
            out[lo:hi] |= sums.max(1, initial=0) >= score - 1e-6
            if hi == len(last):
                break
        return out

    def _parts(self, term: np.ndarray) -> Iterator[slice]:
        """Runs of terms with about CELLS entries of ranges."""
        ends = np.cumsum(self.range_start[term + 1] - self.range_start[term])
        at = 0
        while at < len(term):
            to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + self.cells, "right")))
            yield slice(at, to)
            at = to

    def search(self, terms: list[int], threshold: float | None = None) -> list[tuple[int, float]]:
        """Items (by place) whose weights over the distinct terms add up to the threshold, by block-max WAND."""
        threshold = self.score if threshold is None else threshold
        end = len(self.names)
        lists = []
        for t in terms:
            lo, hi = int(self.start[t]), int(self.start[t + 1])
            lists.append([int(self.item[lo]), lo, hi, t, 0])  # item, place, end, term, block
        found, slack = [], 1e-9

        def forward(x: list, to: int) -> None:
            last, block = self.block_last[x[3]], x[4]
            while block < len(last) and last[block] < to:  # blocks that end before are left out whole
                block += 1
            x[4] = block
            if block == len(last):
                x[0], x[1] = end, x[2]
                return
            lo = max(x[1], int(self.start[x[3]]) + block * self.block)
            hi = min(x[2], int(self.start[x[3]]) + (block + 1) * self.block)
            x[1] = bisect_left(self.items, to, lo, hi)
            x[0] = self.items[x[1]]

        while True:
            lists = sorted((x for x in lists if x[0] < end), key=lambda x: x[0])
            bound, pivot = 0.0, None
            for k, x in enumerate(lists):
                bound += self.most[x[3]]
                if bound >= threshold - slack:
                    pivot = k
                    break
            if pivot is None:
                return found
            at = lists[pivot][0]
            while pivot + 1 < len(lists) and lists[pivot + 1][0] == at:
                pivot += 1
            blocks, until = 0.0, end
            for x in lists[: pivot + 1]:
                last, block = self.block_last[x[3]], x[4]
                while block < len(last) and last[block] < at:
                    block += 1
                if block < len(last):
                    blocks += self.block_most[x[3]][block]
                    until = min(until, last[block] + 1)
            if blocks >= threshold - slack:
                if lists[0][0] == at:
                    got = 0.0
                    for x in lists:
                        if x[0] != at:
                            break
                        got += self.weights[x[1]]
                        forward(x, at + 1)
                    if got >= threshold - slack:
                        found.append((at, got))
                else:
                    for x in lists[:pivot]:
                        if x[0] < at:
                            forward(x, at)
            else:
                if pivot + 1 < len(lists):
                    until = min(until, lists[pivot + 1][0])
                until = max(until, at + 1)
                for x in lists[: pivot + 1]:
                    if x[0] < until:
                        forward(x, until)


def build(items: list[tuple[int, str]], told: Counts | None = None) -> tuple[list[Index], dict[int, tuple[np.ndarray, np.ndarray]], dict[int, tuple[np.ndarray, np.ndarray]]]:
    """Indexes by length class, the trigrams of each item's question and answer, by place in items, and for items of few words, by
    length, the sorted hashes of the whole sequences with their places in items."""
    classes: dict[int, list[tuple[int, np.ndarray]]] = defaultdict(list)
    parts = {}
    whole: dict[int, list[tuple[int, int]]] = defaultdict(list)
    every: list[np.ndarray] = []
    for k, (_, text) in enumerate(items):
        h = _hashes(text)
        if len(h) < MIN_WORDS:
            if len(h):
                whole[len(h)].append((int(tx.grams(h, len(h))[0]), k))
            continue
        every.append(h)
        classes[max(SMALLEST_CLASS, 1 << (len(h) - 1).bit_length())].append((k, h))
        parts[k] = tuple(_trigrams(_hashes(x)) for x in question_and_answer(text))
    told = told or Counts.of(every)
    return [Index(group, span, told=told) for span, group in sorted(classes.items())], parts, {n: tuple(np.array(x, t) for x, t in zip(zip(*sorted(got), strict=True), (np.uint64, np.int64), strict=True)) for n, got in whole.items()}


def _share(part: np.ndarray, of: np.ndarray) -> float:
    return float(np.isin(part, of, assume_unique=True).mean()) if len(part) else 1.0


def _stretches(first: np.ndarray, span: int) -> tuple[np.ndarray, np.ndarray]:
    """Document of each stretch of ``span`` words (the last one of a text is shorter), and each text's first stretch."""
    many = -(-np.diff(first) // span)
    return np.repeat(np.arange(len(many)), many), np.append(0, np.cumsum(many))


def _matches(b: pa.RecordBatch, built: tuple, score: float, overlap: float) -> dict[tuple[int, int], tuple[float, float, float]]:
    """(row, place of the item) to score and shares of a block of texts."""
    indexes, parts, whole = built
    w = tx.Words(*tx.buffers(b.column("text")))
    h = w.hashes(lower=True)
    best: dict[tuple[int, int], tuple[float, float, float]] = {}
    place = np.arange(len(h)) - w.first[w.doc]
    for n, (sequences, where) in whole.items():
        g = tx.grams(h, n)
        lo, hi = np.searchsorted(sequences, g), np.searchsorted(sequences, g, "right")
        for k in np.flatnonzero((hi > lo) & (w.doc[n - 1 :] == w.doc[: len(g)])) if len(g) else ():
            best.update({(int(w.doc[k]), int(item)): (1.0, 1.0, 1.0) for item in where[lo[k] : hi[k]]})
    for index in indexes:
        at = np.searchsorted(index.vocabulary, h)
        at[at == len(index.vocabulary)] = 0
        known = np.flatnonzero(index.vocabulary[at] == h)
        doc, begin = _stretches(w.first, index.span)
        last = np.append(doc[1:] != doc[:-1], True) if len(doc) else np.zeros(0, bool)
        alone = np.append(True, doc[1:] != doc[:-1]) & last if len(doc) else last
        may = index.reachable(begin[w.doc[known]] + place[known] // index.span, at[known], last, score)
        for k in np.flatnonzero(may & (~last | alone)):
            lo = w.first[doc[k]] + (k - begin[doc[k]]) * index.span
            hi = min(lo + 2 * index.span, w.first[doc[k] + 1])
            terms = at[lo:hi][index.vocabulary[at[lo:hi]] == h[lo:hi]]
            found = index.search(np.unique(terms).tolist(), score)
            grams = _trigrams(h[lo:hi]) if found else None
            for which, got in found:
                item = index.names[which]
                q, a = (_share(x, grams) for x in parts[item])
                if q >= overlap and a >= overlap:
                    key = (int(doc[k]), item)
                    best[key] = max(best.get(key, (0.0, 0.0, 0.0)), (got, q, a))
    return best


def _searcher(shared, names: list[int], score: float, overlap: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in tx.blocks(batches):
            rows = sorted(_matches(b, shared.value, score, overlap).items())
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id").take(pa.array([d for (d, _), _ in rows], pa.int64())), pa.array([names[i] for (_, i), _ in rows], pa.int64()), *(pa.array([round(x[k], 6) for _, x in rows], pa.float64()) for k in range(3))],
                ["doc_id", "item_id", "score", "question_overlap", "answer_overlap"],
            )

    return run


def _leaver(shared, score: float, overlap: float):
    """Rows without a match, all columns as they are."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in tx.blocks(batches):
            stay = np.ones(b.num_rows, bool)
            stay[[row for row, _ in _matches(b, shared.value, score, overlap)]] = False
            yield b.filter(pa.array(stay))

    return run


def _hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Items to part, their length and their distinct terms; only those that are indexed."""
    for b in batches:
        got = [(p, h) for p, t in zip(b.column("part").to_pylist(), b.column("text").to_pylist(), strict=True) if len(h := _hashes(t)) >= MIN_WORDS]
        yield pa.RecordBatch.from_arrays([pa.array([p for p, _ in got], pa.int32()), pa.array([len(h) for _, h in got], pa.int64()), pa.array([tx.signed(np.unique(h)) for _, h in got], pa.list_(pa.int64()))], ["part", "n", "terms"])


def _indexes(benchmark: DataFrame) -> Iterator[tuple[list[tuple[int, str]], tuple]]:
    """Items in blocks of bounded size, read one block at a time, with what ``build`` makes of each; counts are over all blocks."""
    from blockgraph.llm.shared import cut

    items = benchmark.select("item_id", F.col("text").cast("string").alias("text")).where(F.col("text").isNotNull()).distinct()
    size = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = -(-size // BLOCK_BYTES)
    if blocks > 1:
        items = cut(items.withColumn("part", F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)).cast("int")), "benchmark")
        terms = cut(items.mapInArrow(_hashed, "part int, n long, terms array<long>"), "benchmark-terms")
        many, words = terms.agg(F.count(F.lit(1)), F.coalesce(F.sum("n"), F.lit(0))).first()
        each = terms.select("part", F.explode("terms").alias("t")).groupBy("t").agg(F.count(F.lit(1)).alias("df"), F.collect_set("part").alias("parts"))
        each = cut(each, "benchmark-df")
    for k in range(blocks):
        told = None
        part = items
        if blocks > 1:
            part = items.where(F.col("part") == k).drop("part")
            rows = each.where(F.array_contains("parts", k)).select("t", "df").toArrow()  # terms of one block
            t, df = rows["t"].to_numpy().view(np.uint64), rows["df"].to_numpy()
            order = np.argsort(t)
            told = Counts(many, words, t[order], df[order])
        got = sorted((tuple(r) for r in part.collect()), key=lambda r: (r[0] is None, r[0] or 0, r[1]))
        built = build(got, told)
        if built[0] or built[2]:
            yield got, built


def find(docs: DataFrame, benchmark: DataFrame, score: float = SCORE, overlap: float = OVERLAP) -> DataFrame:
    """doc_id, item_id, score, question_overlap, answer_overlap: for every row of docs the items that it holds.

    Null or empty texts hold none; null items are left out; repeated rows give repeated matches, repeated items (same id and
    text) count once. Empty tables give an empty result."""
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), docs["text"].cast("string").alias("text"))
    out = None
    for items, built in _indexes(benchmark):
        shared = docs.sparkSession.sparkContext.broadcast(built)
        hits = texts.mapInArrow(_searcher(shared, [i for i, _ in items], score, overlap), SCHEMA)
        out = hits if out is None else out.unionByName(hits)
    return docs.sparkSession.createDataFrame([], SCHEMA) if out is None else out


def remove(docs: DataFrame, benchmark: DataFrame, score: float = SCORE, overlap: float = OVERLAP) -> DataFrame:
    """docs without the rows that hold an item; all their columns stay. Each row is judged by its own text, whatever its doc_id.

    Null and empty texts stay; repeated rows go or stay alike; an empty table of items takes nothing."""
    for _, built in _indexes(benchmark):
        docs = docs.mapInArrow(_leaver(docs.sparkSession.sparkContext.broadcast(built), score, overlap), docs.schema)
    return docs
