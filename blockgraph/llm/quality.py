"""Quality classifier: hashed word n-gram logistic regression by follow-the-regularised-leader updates.

A text's features are its lower-cased words, pairs of neighbouring words, and pairs of neighbouring word shapes (letters,
capitals, digits, marks, word ending, equal to the word before), hashed to 2**BITS weights; each counts 1 / number of features.
Training takes at most ``TRAIN_ROWS`` labelled rows (those with the smallest hash of doc_id: a documented bound, see
``fit``), in a few passes in that order on the driver. Scores are sparse dot products with the broadcast weights
(2**BITS floats: 1 MB) over all rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockgraph.llm.shared import fresh
from blockgraph.llm.text import U, Words, blocks, buffers, grams, mix

BITS = 18
TRAIN_ROWS = 6_000
PASSES = 3
HELD_OUT_FOLD, FOLDS = 0, 5
THRESHOLD = 0.3
ALPHA, BETA, L1, L2, SCALE = 0.5, 1.0, 0.02, 0.05, 12.0


def fold(doc_id, folds: int = FOLDS):
    """crc32 of the id as text, modulo folds; a null id counts as an empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % folds


def _shapes(w: Words, h: np.ndarray) -> np.ndarray:
    """A small code of each word: classes of its bytes, its last byte if that is no letter, length, same as the word before."""
    kind = np.full(256, 8, np.uint8)
    kind[97:123], kind[65:91], kind[48:58], kind[128:] = 1, 2, 4, 1
    seen = np.bitwise_or.reduceat(kind[w.buf], np.stack([w.start, w.end - 1], 1).ravel())[::2] if len(w.start) else np.zeros(0, np.uint8)
    last = w.buf[w.end - 1] if len(w.start) else np.zeros(0, np.uint8)
    last = np.where((kind[last] == 1) | (kind[last] == 2) | (last >= 128), 0, last)
    seen |= kind[w.buf[w.end - 1]] if len(w.start) else seen
    length = np.minimum(w.end - w.start, 40) // 5
    same = np.zeros(len(h), np.uint64)
    same[1:] = (h[1:] == h[:-1]) & (w.doc[1:] == w.doc[:-1])
    return mix(seen.astype(np.uint64) | last.astype(np.uint64) << U(8) | length.astype(np.uint64) << U(16) | same << U(24), 3)


def features(buf: np.ndarray, off: np.ndarray, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """Feature numbers of a block of texts and how many each text has, in the texts' order."""
    w = Words(buf, off)
    h = w.hashes(lower=True)
    s = _shapes(w, h)
    n = len(h)
    out = np.zeros((n, 4), np.uint64)
    out[:, 0], out[:, 2] = mix(h, 4), s
    inner = np.zeros(n, bool)
    if n > 1:
        inner[:-1] = w.doc[1:] == w.doc[:-1]
        out[:-1, 1], out[:-1, 3] = mix(grams(h, 2), 5), mix(grams(s, 2), 6)
    use = np.ones((n, 4), bool)
    use[:, 1] = use[:, 3] = inner
    return (out[use] >> U(64 - bits)).astype(np.int32), np.bincount(w.doc, weights=use.sum(1), minlength=len(off) - 1).astype(np.int64)


class Ftrl:
    """Per-coordinate follow-the-regularised-leader for logistic loss; weight 0 of the last slot is the constant."""

    def __init__(self, size: int, alpha: float = ALPHA, beta: float = BETA, l1: float = L1, l2: float = L2):
        self.z, self.n, self.rates = np.zeros(size), np.zeros(size), (alpha, beta, l1, l2)

    def weights(self, at=slice(None)) -> np.ndarray:
        alpha, beta, l1, l2 = self.rates
        z, n = self.z[at], self.n[at]
        return np.where(np.abs(z) > l1, (np.sign(z) * l1 - z) / ((beta + np.sqrt(n)) / alpha + l2), 0.0)

    def update(self, at: np.ndarray, x: np.ndarray, y: int) -> float:
        """at: distinct coordinates. Returns the probability before the update."""
        w = self.weights(at)
        p = 1 / (1 + np.exp(-np.clip(w @ x, -35, 35)))
        g = (p - y) * x
        n = self.n[at]
        self.z[at] += g - (np.sqrt(n + g * g) - np.sqrt(n)) / self.rates[0] * w
        self.n[at] = n + g * g
        return float(p)


def train(rows: list[tuple[np.ndarray, np.ndarray, int]], bits: int = BITS, passes: int = PASSES) -> np.ndarray:
    """Weights (the last one is the constant) from (features, counts, label) in the order given."""
    model = Ftrl(2**bits + 1)
    for _ in range(passes):
        for at, x, y in rows:
            model.update(np.append(at, 2**bits), np.append(x * (SCALE / max(x.sum(), 1)), 1.0), y)
    return model.weights().astype(np.float32)


def _featurise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in blocks(batches):
        at, n = features(*buffers(b.column("text")))
        cuts, lists, counts = np.concatenate([[0], np.cumsum(n)]), [], []
        for i in range(b.num_rows):
            f, c = np.unique(at[cuts[i] : cuts[i + 1]], return_counts=True)
            lists.append(f)
            counts.append(c.astype(np.int32))
        yield pa.RecordBatch.from_arrays([b.column("k"), b.column("y"), pa.array(lists, pa.list_(pa.int32())), pa.array(counts, pa.list_(pa.int32()))], ["k", "y", "f", "c"])


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", rows: int = TRAIN_ROWS) -> np.ndarray:
    """Weights from the labelled rows of docs whose fold is not the held-out one, at most ``rows`` of them.

    Labels that are null or whose text is missing are not used; of repeated labels of a document the largest counts.
    Without any training row all weights are 0 and every score is one half."""
    known = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & (fold(F.col("doc_id")) != HELD_OUT_FOLD))
    known = known.groupBy("doc_id").agg(F.max(label).cast("int").alias("y")).withColumn("k", F.md5(F.col("doc_id").cast("string")))
    known = known.orderBy("k").limit(rows)
    texts = docs.select("doc_id", docs["text"].cast("string").alias("text"))
    chosen = texts.join(F.broadcast(known), "doc_id").groupBy("k", "y").agg(F.min("text").alias("text"))  # one text for a repeated id
    got = chosen.select("k", "y", "text").mapInArrow(_featurise, "k string, y int, f array<int>, c array<int>").toArrow()
    examples = [(k, f.values.to_numpy(), c.values.to_numpy(), y) for b in got.to_batches() for k, y, f, c in zip(b["k"].to_pylist(), b["y"].to_pylist(), b["f"], b["c"], strict=True)]
    examples = [x[1:] for x in sorted(examples, key=lambda x: x[0]) if len(x[1])]  # views of the batches: the features lie in memory once
    weights = train(examples[:rows])
    del got, examples
    pa.default_memory_pool().release_unused()
    return weights


def score(docs: DataFrame, weights: np.ndarray, threshold: float = THRESHOLD, names: tuple[str, str] = ("score", "predicted")) -> DataFrame:
    """All columns of docs with two more, ``names``: the score (0 to 1) and 1 if it is at least the threshold; null texts score as
    empty ones, an empty table gives an empty one, repeated rows repeat. docs must not have columns of these names."""
    from pyspark.sql.types import DoubleType, IntegerType, StructType

    if {n.lower() for n in names} & {c.lower() for c in docs.columns}:
        raise ValueError(f"docs has one of the columns {names}; give other names")
    shared = docs.sparkSession.sparkContext.broadcast(weights)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w = shared.value
        for b in blocks(batches):
            at, n = features(*buffers(b.column("text")))
            sums = np.concatenate([[0.0], np.cumsum(w[at], dtype=np.float64)])
            ends = np.cumsum(n)
            margin = w[-1] + SCALE * (sums[ends] - sums[ends - n]) / np.maximum(n, 1)
            p = 1 / (1 + np.exp(-np.clip(margin, -35, 35)))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(p), pa.array((p >= threshold).astype(np.int32))], [*b.schema.names, *names])

    return docs.mapInArrow(run, StructType([*docs.schema.fields]).add(names[0], DoubleType()).add(names[1], IntegerType()))


def keep_good(docs: DataFrame, weights: np.ndarray, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of docs that the classifier does not reject, with all their columns."""
    names = fresh("score", docs.columns), fresh("predicted", docs.columns)
    return score(docs, weights, threshold, names).where(F.col(names[1]) == 1).select(*docs.columns)


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted of every row of docs; further columns are left out, an empty table gives an empty one."""
    texts = docs.select("doc_id", docs["text"].cast("string").alias("text"))
    out = score(texts, fit(docs, labels))
    return out.select("doc_id", (fold(F.col("doc_id")) == HELD_OUT_FOLD).alias("held_out"), "score", "predicted")
