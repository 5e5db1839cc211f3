"""LM scoring with a log-frequency Bloom filter.

A count c is stored as its level, 1 + floor(log(c) / log(BASE)): the n-gram goes into the filter once for each level up to its own,
so asking level after level until one is absent gives the count back up to the base. Every unigram and bigram of the training
texts is stored, at any size of the corpus; the filter has ``BITS_PER_ENTRY`` bits for each entry.

Such a filter grows with the corpus, so no bound of its size could be proven and it is not broadcast as a whole: it lies in slices
by hash, and each slice goes to the one worker that answers for it. Texts are kept in blocks (packed, one row each). A block sends its
distinct n-grams, sorted, with how often its training texts hold them, to the slices that they belong to: one exchange, that serves
counting and asking alike. A worker adds the counts up, builds its slice, asks it for every n-gram that came, and sends levels
(and the words' counts) back to the blocks, where the texts wait.

p(w | v) = mix * count(v, w) / count(v) + (1 - mix) * (count(w) + 0.5) / M; a text begins and ends with the end token. Levels are
read as their lower ends for bigrams and as their upper ends for what they are divided by; words as the middles of their levels,
and M is what those, 0.5 more each, and 0.5 for all unknown words add up to. So the probabilities of a history add up to no more
than one but for the filter's false positives.

The base score is exact: a slice also answers with its words' counts. Words are told apart by 64 bits, bigrams by ``PAIR_BYTES`` bytes.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockgraph.llm import text as tx
from blockgraph.llm.shared import cut
from blockgraph.llm.text import U
from blockgraph.storage import settings

HELD_OUT_FOLD, FOLDS = 1, 5
BASE = 1.5
BITS_PER_ENTRY = 12
LEAST_BITS = 1 << 10
HASHES = 4
MIX = 0.2
BLOCK_BYTES = 8 << 20
PART_TOKENS = 1_500_000
LEAST_PARTS = 64
PAIR_BYTES = 6
ROWS = 16
END = U(0x5D0C7E4D0C7E4D01)
LEVELS = 120


def training(doc_id) -> F.Column:
    """Whether crc32 of the id as text (null: empty) is not in the held-out fold."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % FOLDS != HELD_OUT_FOLD


def tokens(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Token hashes of each text, the end token last, and how many each has."""
    w = tx.Words(*tx.buffers(column))
    n = w.count + 1
    out = np.full(n.sum(), END, np.uint64)
    out[np.arange(len(w.doc)) + w.doc] = w.hashes(lower=True)
    return out, n


def bigrams(t: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The token before each token (the end token before a text's first) and the hash of both, of PAIR_BYTES bytes."""
    before = np.empty_like(t)
    before[1:] = t[:-1]
    if len(t):
        before[np.append(0, np.cumsum(n)[:-1])] = END
    drop = U(64 - 8 * PAIR_BYTES)
    return before, tx.mix(tx.mix(before, 40) + t * U(0x9FB21C651E98DF25), 41) >> drop << drop


def level(count: np.ndarray) -> np.ndarray:
    """1 and more for counts of 1 and more, 0 for 0."""
    return np.where(count > 0, np.floor(np.log(np.maximum(count, 1)) / np.log(BASE) + 1e-9).astype(np.int64) + 1, 0)


def lower_end(levels: np.ndarray) -> np.ndarray:
    """The smallest whole count of a level; 0 for level 0."""
    return np.where(levels > 0, np.ceil(BASE ** (levels - 1.0) - 1e-6), 0.0)


def upper_end(levels: np.ndarray) -> np.ndarray:
    return np.where(levels > 0, np.maximum(lower_end(levels), np.ceil(BASE ** np.asarray(levels, float) - 1e-6) - 1), 0.0)


def middle(levels: np.ndarray) -> np.ndarray:
    return np.sqrt(lower_end(levels) * upper_end(levels))


def mass(spread: np.ndarray) -> float:
    """What words add up to, read off their levels, the unknown ones together as one half; spread[k]: words of level k."""
    k = np.arange(1, len(spread))
    return float((spread[1:] * (middle(k) + 0.5)).sum()) + 0.5


def smoothed(pair: np.ndarray, history: np.ndarray, word: np.ndarray, whole: float) -> np.ndarray:
    """Probabilities from the levels of bigrams, of their first and of their second words; whole: see ``mass``."""
    return MIX * np.minimum(lower_end(pair) / np.maximum(upper_end(history), 1.0), 1.0) + (1 - MIX) * (middle(word) + 0.5) / whole


class Slice:
    """One slice of the filter, of ``size`` bits."""

    def __init__(self, size: int):
        self.size = -(-size // 8) * 8
        self.bits = np.zeros(self.size // 8, np.uint8)

    @staticmethod
    def of(h: np.ndarray, parts: int) -> np.ndarray:
        """The slice that a hash belongs to; ascending with the hash."""
        return ((h >> U(32)) * U(parts) >> U(32)).astype(np.int64)

    def _places(self, h: np.ndarray, k: int) -> Iterator[np.ndarray]:
        x = tx.mix(h + U(k * 0xA24BAED4963EE407 % 2**64), 42)
        step = (x >> U(33)) | U(1)
        x = x & U(0xFFFFFFFF)
        for i in range(HASHES):
            yield ((x + U(i) * step) % U(self.size)).astype(np.int64)

    def store(self, h: np.ndarray, levels: np.ndarray) -> None:
        """Each hash once for each level up to its own."""
        for k in range(1, int(levels.max(initial=0)) + 1):
            for at in self._places(h[levels >= k], k):
                np.bitwise_or.at(self.bits, at >> 3, np.left_shift(1, at & 7).astype(np.uint8))

    def holds(self, h: np.ndarray, k: int) -> np.ndarray:
        out, rows = np.zeros(len(h), bool), np.arange(len(h))
        for at in self._places(h, k):
            at = at[rows]
            rows = rows[(self.bits[at >> 3] >> (at & 7).astype(np.uint8)) & 1 > 0]
        out[rows] = True
        return out

    def levels(self, h: np.ndarray) -> np.ndarray:
        """The highest level up to which every one from 1 on is held; 0 if the first is not."""
        out, rows = np.zeros(len(h), np.uint8), np.arange(len(h))
        for k in range(1, LEVELS + 1):
            rows = rows[self.holds(h[rows], k)]
            if not len(rows):
                break
            out[rows] = k
        return out


def _packed(x: np.ndarray, width: int = 8) -> bytes:
    """The ``width`` highest bytes of each value, byte plane by byte plane: planes that hardly change compress well."""
    return x.view(np.uint8).reshape(-1, x.itemsize)[:, x.itemsize - width :].T.tobytes()


def _unpacked(data: pa.Scalar, width: int = 8, kind=np.uint64) -> np.ndarray:
    planes = np.frombuffer(data.as_buffer(), np.uint8).reshape(width, -1)
    size = np.dtype(kind).itemsize
    out = np.zeros((planes.shape[1], size), np.uint8)
    out[:, size - width :] = planes.T
    return out.view(kind).ravel()


def _pack(limit: int) -> Callable:
    """Texts to one row for each block of about ``limit`` bytes, compressed, with its number of tokens."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = TaskContext.get().partitionId() << 32
        for b in tx.blocks(batches, limit=limit):
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, b.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
                out.write_batch(b)
            many = sum(tx.Words(*tx.buffers(x.column("text"))).count.sum() + x.num_rows for x in tx.blocks([b]))
            yield pa.RecordBatch.from_arrays([pa.array([at], pa.int64()), pa.array([many], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["block", "tokens", "frame"])
            at += 1

    return run


def _unpack(frame: pa.Scalar) -> tuple[pa.RecordBatch, np.ndarray, np.ndarray]:
    """A block's rows, their tokens and how many each row has."""
    with pa.ipc.open_stream(frame.as_buffer()) as stream:
        b = stream.read_next_batch()
    t, n = zip(*(tokens(x.column("text")) for x in tx.blocks([b])), strict=True)
    return b, np.concatenate(t), np.concatenate(n)


def _send(parts: int) -> Callable:
    """Blocks to their distinct words and bigrams, sorted, with their counts in training texts, by the slice that they belong to."""

    def distinct(x: np.ndarray, learnt: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        order = np.argsort(x, kind="stable")
        x = x[order]
        head = np.flatnonzero(np.append(True, x[1:] != x[:-1]))
        return x[head], np.add.reduceat(learnt[order].astype(np.uint32), head, dtype=np.uint32)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for block, frame in zip(b.column("block").to_pylist(), b.column("frame"), strict=True):
                rows, t, n = _unpack(frame)
                learnt = np.repeat(~rows.column("held_out").to_numpy(zero_copy_only=False), n)
                both = [distinct(t, learnt), distinct(bigrams(t, n)[1], learnt)]
                cuts = [np.searchsorted(Slice.of(h, parts), np.arange(parts + 1)) for h, _ in both]
                keep = [p for p in range(parts) if any(c[p + 1] > c[p] for c in cuts)]
                data = [pa.array([f(x[c[p] : c[p + 1]]) for p in keep], pa.binary()) for (h, m), c, width in zip(both, cuts, (8, PAIR_BYTES), strict=True) for x, f in ((h, lambda x, width=width: _packed(x, width)), (m, lambda x: _packed(x, 4)))]
                yield pa.RecordBatch.from_arrays([pa.array(keep, pa.int32()), pa.array([block] * len(keep), pa.int64()), *data], ["part", "block", "words", "word_counts", "pairs", "pair_counts"])

    return run


def _answer(each: int, least: int) -> Callable:
    """Rows sorted by part to levels for each block, and one row (block null) of what the part holds of words.

    each: bits for an entry of the filter. least: bits of a slice at least."""
    names = ["block", "part", "known", "words", "pairs", "total", "spread"]

    def out(part: int, rows: list[tuple]) -> Iterator[pa.RecordBatch]:
        told = []
        for k in (1, 3):
            h, back = np.unique(np.concatenate([r[k] for r in rows]), return_inverse=True)
            told.append((h, np.bincount(back, weights=np.concatenate([r[k + 1] for r in rows]), minlength=len(h)).astype(np.int64), back))
        up = [np.minimum(level(c), LEVELS) for _, c, _ in told]
        one = Slice(max(least, int(sum(u.sum() for u in up)) * each))
        for (h, _, _), u in zip(told, up, strict=True):
            one.store(h, u)
        cuts = [np.cumsum([len(r[k]) for r in rows])[:-1] for k in (1, 3)]
        known = np.split(told[0][1][told[0][2]], cuts[0])
        asked = [np.split(one.levels(h)[back], c) for (h, _, back), c in zip(told, cuts, strict=True)]
        spread = np.bincount(up[0], minlength=LEVELS + 1)
        spread[0] = 0
        yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.array([part], pa.int32()), *(pa.nulls(1, pa.binary()) for _ in range(3)), pa.array([int(told[0][1].sum())], pa.int64()), pa.array([spread], pa.list_(pa.int64()))], names)
        for lo in range(0, len(rows), ROWS):
            few = range(lo, min(lo + ROWS, len(rows)))
            data = [pa.array([f(x[i]) for i in few], pa.binary()) for f, x in ((_packed, known), (np.ndarray.tobytes, asked[0]), (np.ndarray.tobytes, asked[1]))]
            yield pa.RecordBatch.from_arrays([pa.array([rows[i][0] for i in few], pa.int64()), pa.array([part] * len(few), pa.int32()), *data, pa.nulls(len(few), pa.int64()), pa.nulls(len(few), pa.list_(pa.int64()))], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, rows = None, []
        for b in batches:
            for part, block, *x in zip(b.column("part").to_pylist(), b.column("block").to_pylist(), *(b.column(c) for c in ("words", "word_counts", "pairs", "pair_counts")), strict=True):
                if part != at and rows:
                    yield from out(at, rows)
                    rows = []
                at = part
                rows.append((block, _unpacked(x[0]), _unpacked(x[1], 4, np.uint32), _unpacked(x[2], PAIR_BYTES), _unpacked(x[3], 4, np.uint32)))
        if rows:
            yield from out(at, rows)

    return run


def _sum(x: np.ndarray, n: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0.0], np.cumsum(x, dtype=np.float64)])
    ends = np.cumsum(n)
    return total[ends] - total[ends - n]


def _score(total: int, distinct: int, whole: float) -> Callable:
    """Rows sorted by block and part (the block's texts first, then the answers of the slices) to scores."""
    below = total + 0.5 * (distinct + 1)

    def out(frame: pa.Scalar, answers: list[tuple]) -> pa.RecordBatch:
        b, t, n = _unpack(frame)
        before, pair = bigrams(t, n)
        seen, back = np.unique(t, return_inverse=True)
        known = np.concatenate([_unpacked(x[0], 8, np.int64) for x in answers])  # slices ascend with the hashes
        up, both = (np.frombuffer(b"".join(x[k].as_py() for x in answers), np.uint8).astype(np.int64) for k in (1, 2))
        p = smoothed(both[np.unique(pair, return_inverse=True)[1]], up[np.searchsorted(seen, before)], up[back], whole)
        base = np.log10((known + 0.5) / below)[back]
        return pa.RecordBatch.from_arrays(
            [b.column("doc_id"), b.column("held_out"), pa.array(n.astype(np.int64)), pa.array(_sum((known > 0)[back], n).astype(np.int64)), pa.array(_sum(base, n)), pa.array(_sum(np.log10(p), n))],
            ["doc_id", "held_out", "n_tokens", "n_known", "base_score", "score"],
        )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        frame, answers = None, []
        for b in batches:
            for part, *x in zip(b.column("part").to_pylist(), b.column("known"), b.column("words"), b.column("pairs"), strict=True):
                if part >= 0:
                    answers.append(x)
                    continue
                if frame is not None:
                    yield out(frame, answers)
                frame, answers = x[0], [(*(pa.scalar(b"", pa.binary()),) * 3,)]  # a block of no rows has no answers
        if frame is not None:
            yield out(frame, answers)

    return run


class Model:
    """Texts (doc_id, held_out, text), and what was learnt from those that are not held out: ``n`` tokens, ``v`` distinct ones, how the
    distinct ones spread over the levels, and the levels of every block's n-grams."""

    def __init__(self, docs: DataFrame):
        spark = docs.sparkSession
        packed = docs.select("doc_id", "held_out", "text").mapInArrow(_pack(BLOCK_BYTES), "block long, tokens long, frame binary")
        self.frames = cut(packed, "lm-texts", free=True)
        self.parts = max(LEAST_PARTS, -(-(self.frames.agg(F.sum("tokens")).first()[0] or 0) // PART_TOKENS))
        sent = self.frames.select("block", "frame").mapInArrow(_send(self.parts), "part int, block long, words binary, word_counts binary, pairs binary, pair_counts binary")
        met = sent.repartition(self.parts, "part").sortWithinPartitions("part", "block")
        with settings(spark, spark__sql__execution__arrow__maxRecordsPerBatch=ROWS):  # rows of up to some MB
            self.answers = cut(met.mapInArrow(_answer(BITS_PER_ENTRY, LEAST_BITS), "block long, part int, known binary, words binary, pairs binary, total long, spread array<long>"), "lm-levels", free=True)
        told = self.answers.where("block is null")
        self.n = told.agg(F.coalesce(F.sum("total"), F.lit(0))).first()[0]
        self.spread = np.zeros(LEVELS + 1)
        for k, m in told.select(F.posexplode("spread").alias("k", "m")).groupBy("k").agg(F.sum("m")).collect():  # LEVELS rows
            self.spread[k] = m
        self.v = int(self.spread.sum())

    def scores(self) -> DataFrame:
        """doc_id, held_out, n_tokens, n_known, base_score, score for each text."""
        none = (F.lit(None).cast("binary").alias(c) for c in ("words", "pairs"))
        texts = self.frames.select("block", F.lit(-1).alias("part"), F.col("frame").alias("known"), *none)
        answers = self.answers.where("block is not null").select("block", "part", "known", "words", "pairs")
        back = texts.unionByName(answers).repartition(self.parts, "block").sortWithinPartitions("block", "part")
        return back.mapInArrow(_score(self.n, self.v, mass(self.spread)), "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double")


def score(docs: DataFrame, held_out: F.Column | None = None) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of each row of docs (null text: empty); the model learns
    from the rows that are not held out (a predicate over docs, by default the held-out fold of the ids).

    Null ids are trained on or held out as an empty id text; repeated rows count as often as they stand. With no training
    token every word counts as unknown. An empty table gives an empty one; further columns are left out."""
    held_out = ~training(F.col("doc_id")) if held_out is None else held_out
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(held_out, F.lit(False)).alias("held_out"), docs["text"].cast("string").alias("text"))
    model = Model(base)
    return model.scores().select("doc_id", "held_out", "n_tokens", "n_known", F.lit(int(model.n)).cast("long").alias("train_tokens"), "base_score", "score")
