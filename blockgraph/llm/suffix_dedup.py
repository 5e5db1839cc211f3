"""Suffix-array dedup: bytes covered by a 100-byte string that also starts earlier are removed.

Candidates come from ``repeats``; where several contents meet at one anchor, their suffixes are sorted to the depth of a
window by bucket-pointer refinement: suffixes are dealt into buckets by their first ``q`` bytes (at most 8), then each bucket of
more than one is split by the bucket identifiers of the suffixes that start as many bytes later as the order is known for. The
identifiers split in one round are what the next round sorts by, so the known depth doubles: 8, 16, 32, 64, 100.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockgraph.llm import text as tx
from blockgraph.llm.repeats import Rows, Rule, repeated_runs
from blockgraph.llm.shared import fresh

SPAN = 100
Q = 8
RULE = Rule(span=SPAN, gram=24, words=False, across=False)


def refine(first: np.ndarray, left: np.ndarray, q: int, span: int) -> np.ndarray:
    """Bucket identifiers of depth ``span`` from ones of depth q.

    first: identifiers of depth q of every suffix in text order. left: bytes from each suffix to its segment's end. A suffix
    with fewer bytes left than the depth is in a bucket of its own."""
    pointer = first.astype(np.int64)
    depth = q
    while depth < span:
        step = min(depth, span - depth)
        live = np.flatnonzero(left >= depth + step)
        pair = pointer[live]
        size = np.bincount(pair) if len(pair) else np.zeros(0, np.int64)
        split = size[pair] > 1 if len(pair) else np.zeros(0, bool)  # a bucket of one is in place
        rows = live[split]
        new = np.arange(len(pointer), dtype=np.int64)
        if len(rows):
            keys = pointer[rows] * (int(pointer.max()) + 1) + pointer[rows + step]
            order = np.argsort(keys, kind="stable")
            k = keys[order]
            head = np.append(True, k[1:] != k[:-1])
            lead = rows[order][np.flatnonzero(head)][np.cumsum(head) - 1]
            new[rows[order]] = lead  # an identifier is its first suffix in text order
        pointer = new
        depth += step
    return pointer


def window_classes(group: np.ndarray, seg: np.ndarray, off: np.ndarray, span: int, q: int) -> np.ndarray:
    """An identifier for each suffix of the segments: equal where group and the first ``span`` bytes are equal."""
    of = np.repeat(np.arange(len(off) - 1), np.diff(off))
    left = off[of + 1] - np.arange(len(seg))
    live = np.flatnonzero(left >= q)
    first = np.arange(len(seg), dtype=np.int64)
    if len(live):
        head = np.zeros(len(seg) - q + 1, np.uint64)
        for k in range(q):  # the first q bytes as a number
            head = head << np.uint64(8) | seg[k : k + len(head)]
        head, where = head[live], group[of[live]]
        order = np.lexsort((head, where))
        new = np.append(True, (head[order][1:] != head[order][:-1]) | (where[order][1:] != where[order][:-1]))
        first[live[order]] = live[order][np.flatnonzero(new)][np.cumsum(new) - 1]
    return refine(first, left, q, span)


def resolve(group, doc, row, s, n, seg, off, rule: Rule, q: int = Q) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Windows (segment, offset, length) whose content also starts at a smaller (doc, start, row) in the same group."""
    name = window_classes(group, seg, off, rule.span, min(q, rule.span, 8))
    of = np.repeat(np.arange(len(n)), n)
    at = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
    name = name[off[of] + at]
    many = np.bincount(name, minlength=1)[name] > 1
    of, at, name = of[many], at[many], name[many]
    place = s[of] + at
    order = np.lexsort((row[of], place, doc[of], name))
    of, at, name, place = of[order], at[order], name[order], place[order]
    head = np.append(True, name[1:] != name[:-1]) if len(name) else np.zeros(0, bool)
    lead = np.flatnonzero(head)[np.cumsum(head) - 1] if len(name) else np.zeros(0, np.int64)
    later = (doc[of] != doc[of][lead]) | (place != place[lead]) | (row[of] != row[of][lead])
    return of[later], at[later], np.full(int(later.sum()), rule.span)


def kept_bytes(raw: bytes, runs: list[int] | None) -> tuple[bytes, int, int]:
    """What is left without the runs, how many bytes and runs went."""
    if not runs:
        return raw, 0, 0
    out, at, spans = [], 0, 0
    for a, b in zip(runs[::2], runs[1::2], strict=True):
        b = min(b, len(raw))
        if a < b:
            out.append(raw[at:a])
            at, spans = b, spans + 1
    out.append(raw[at:])
    kept = b"".join(out)
    return kept, len(raw) - len(kept), spans


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in tx.blocks(batches, "text", 4 << 20):
        rows = []
        for t, r in zip(b.column("text").to_pylist(), b.column("runs").to_pylist(), strict=True):
            raw = (t or "").encode()
            kept, gone, spans = kept_bytes(raw, r)
            rows.append((len(raw), gone, spans, hashlib.sha256(kept).hexdigest()))
        cols = list(zip(*rows, strict=True)) if rows else [[]] * 4
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), *(pa.array(c, pa.int64()) for c in cols[:3]), pa.array(cols[3], pa.string())], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])


def _cut_text(name: str) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in tx.blocks(batches, "text", 4 << 20):
            at = b.schema.get_field_index("text")
            new = [None if t is None else kept_bytes(t.encode(), r)[0].decode("utf-8", "ignore") for t, r in zip(b.column("text").to_pylist(), b.column(name).to_pylist(), strict=True)]
            cols = [pa.array(new, pa.string()) if i == at else c for i, c in enumerate(b.columns)]
            keep = [i for i, f in enumerate(b.schema.names) if f != name]
            yield pa.RecordBatch.from_arrays([cols[i] for i in keep], [b.schema.names[i] for i in keep])

    return run


def digest(docs: DataFrame, rule: Rule = RULE) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 for each row of docs; see ``repeats`` for nulls and repeated rows.

    An empty table gives an empty one; further columns are left out."""
    rows = Rows(docs.select("doc_id", docs["text"].cast("string").alias("text")))
    marked = rows.with_runs(repeated_runs(rows, rule, resolve), "runs")
    return marked.mapInArrow(_digest, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def remove(docs: DataFrame, rule: Rule = RULE) -> DataFrame:
    """docs with repeated bytes cut out of ``text`` (parts of characters left at a cut go too) and ``n_chars``, if there is such
    a column, counted anew. Null texts stay null; all other columns stay, whatever their names."""
    rows, name = Rows(docs), fresh("runs", docs.columns)
    out = rows.with_runs(repeated_runs(rows, rule, resolve), name).mapInArrow(_cut_text(name), docs.schema)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out
