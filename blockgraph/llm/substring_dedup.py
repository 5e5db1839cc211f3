"""Substring dedup by seed and extend: words covered by 13 consecutive words that a smaller doc_id has too are removed.

Documents meet at winnowed anchors of five words (``repeats``). Where the surroundings differ, the match is extended from the
anchor word by word, to the left and to the right, for all documents of the anchor at once: after each step the documents
that still agree form a class. For every extension to the left, the longest one to the right that a smaller document shares
makes a repeat that is maximal within the segment; those of at least 13 words count. Neighbouring anchors share words, so what
they give joins up to the maximal repeats of the texts.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from blockgraph.llm import text as tx
from blockgraph.llm.repeats import Rows, Rule, repeated_runs
from blockgraph.llm.text import U

SPAN = 13
RULE = Rule(span=SPAN, gram=5, words=True, across=True)


def _classes(key: np.ndarray) -> np.ndarray:
    return np.unique(key, return_inverse=True)[1].astype(np.int64)


def resolve(group, doc, row, s, n, seg, off, rule: Rule) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Repeats (segment, offset, length) of span words and more that a smaller document of the group has too."""
    length = np.diff(off)
    # the anchor's place: all windows of a segment hold it, so it starts between the last window's start and the first one's end
    sums = np.zeros(len(seg) + 1, dtype=np.uint64)
    np.cumsum(seg * tx._pow(tx._P, len(seg)), out=sums[1:])
    m = len(seg) - rule.gram + 1
    gram = tx.mix((sums[rule.gram :] - sums[:m]) * tx._pow(tx._PINV, len(seg) + 1)[:m], 2)
    low = (gram >> U(30)).astype(np.int64)
    reach = rule.span - rule.gram
    place = np.full(len(n), -1)
    best = np.full(len(n), np.iinfo(np.int64).max)
    for k in range(reach + 1):  # leftmost smallest gram of the last window
        at = n - 1 + k
        v = low[off[:-1] + at]
        better = v < best
        best, place = np.where(better, v, best), np.where(better, at, place)
    big = np.int64(2**31)
    left = [group.astype(np.int64)]
    for k in range(1, reach + 1):
        ok = place >= k
        word = seg[np.where(ok, off[:-1] + place - k, 0)]
        key = tx.mix(word, 13) ^ tx.mix(left[-1].astype(np.uint64), 14)
        left.append(np.where(ok, _classes(key), -1 - np.arange(len(n))))
    right = [group.astype(np.int64)]
    for k in range(1, reach + 1):
        p = place + rule.gram + k - 1
        ok = p < length
        word = seg[np.where(ok, off[:-1] + p, 0)]
        key = tx.mix(word, 13) ^ tx.mix(right[-1].astype(np.uint64), 14)
        right.append(np.where(ok, _classes(key), -1 - np.arange(len(n))))
    found = []
    for k in range(reach + 1):  # k words to the left of the anchor
        rows = np.flatnonzero(place >= k)
        for r in range(reach, reach - k - 1, -1):  # the longest way to the right first
            here = rows[place[rows] + rule.gram + r <= length[rows]]
            if not len(here):
                continue
            key = left[k][here] * big + right[r][here]
            order = np.lexsort((doc[here], key))
            here, key = here[order], key[order]
            head = np.append(True, key[1:] != key[:-1])
            least = doc[here][np.flatnonzero(head)][np.cumsum(head) - 1]
            here = here[doc[here] > least]
            found.append((here, place[here] - k, np.full(len(here), k + rule.gram + r)))
            rows = rows[~np.isin(rows, here, assume_unique=True)]  # shorter ones lie inside
    if not found:
        return (np.zeros(0, np.int64),) * 3
    return tuple(np.concatenate(c) for c in zip(*found, strict=True))


def kept_words(buf: np.ndarray, start: np.ndarray, end: np.ndarray, runs: list[int] | None) -> tuple[bytes, int]:
    """The words outside the runs, joined by one blank, and how many went."""
    keep = np.ones(len(start), bool)
    for a, b in zip((runs or [])[::2], (runs or [])[1::2], strict=True):
        keep[a:b] = False
    raw = buf.tobytes()
    words = [raw[i:j] for i, j in zip(start[keep].tolist(), end[keep].tolist(), strict=True)]
    return b" ".join(words), int(len(keep) - keep.sum())


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in tx.blocks(batches):
        buf, off = tx.buffers(b.column("text"))
        w = tx.Words(buf, off)
        gone, sha = [], []
        for i, runs in enumerate(b.column("runs").to_pylist()):
            lo, hi = w.first[i], w.first[i + 1]
            kept, n = kept_words(buf[off[i] : off[i + 1]], w.start[lo:hi] - off[i], w.end[lo:hi] - off[i], runs)
            gone.append(n)
            sha.append(hashlib.sha256(kept).hexdigest())
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(w.count.astype(np.int64)), pa.array(gone, pa.int64()), pa.array(sha, pa.string())], ["doc_id", "n_words", "n_removed", "kept_sha256"])


def digest(docs: DataFrame, rule: Rule = RULE) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 for each row of docs; see ``repeats`` for nulls and repeated rows.

    An empty table gives an empty one; further columns are left out."""
    rows = Rows(docs.select("doc_id", docs["text"].cast("string").alias("text")))
    marked = rows.with_runs(repeated_runs(rows, rule, resolve), "runs")
    return marked.mapInArrow(_digest, "doc_id long, n_words long, n_removed long, kept_sha256 string")
