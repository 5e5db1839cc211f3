"""Repeated runs of units (bytes or words) across documents: which windows of ``span`` units also start earlier.

1. *Anchors.* Every window of ``span`` units has one anchor, the smallest of the hashes of its ``gram``-unit grams (leftmost of
   equals). The anchor depends on the window's content alone, so equal windows meet at equal anchors, and neighbouring
   windows mostly share one: a *segment* is the run of units of the windows of one anchor.
2. *Before the shuffle*, each task keeps one row for each anchor and segment content; other occurrences are known to repeat.
3. *One shuffle by anchor.* Rows of one anchor whose segments have the same content are settled by order alone. Where one
   anchor has several contents, the first occurrence of each goes on. Anchors found to be very common in a sample of the rows are
   shuffled by anchor and content instead, so that no task gets all of them (the sample decides where rows go, not what comes out).
4. *Contents meet.* Those segments are cut out of the texts and given to the operator's own ``resolve`` (suffix buckets, or
   seed extension), all segments of an anchor together. Common anchors, and ones with more than ``HOT`` contents, are settled window by
   window through a grouped minimum instead, which is exact as well and has no bound on the group.
5. The removed runs of each row come together by row.

Null texts are empty; a null doc_id is the smallest one. Rows are told apart by doc_id and, where the ids of a table repeat, by the
hash of their text: runs belong to a row, ids only order. Of windows at the same start of rows with one doc_id those of the row with the smaller hash
are the earlier ones; rows that repeat id and text get the same result.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blockgraph.llm import text as tx
from blockgraph.llm.shared import cut, fresh, small
from blockgraph.llm.text import U

HOT = 10_000
SAMPLE_ROWS, SAMPLE_HOT, HOT_ANCHORS = 5_000, 250, 4096
PRE_ROWS = 1_000_000
PIECE = 2 << 20
_POS = 30
NULL_ID = -(2**63)
ANCHORS = "h long, g long, doc long, row long, s int, n int, known boolean, hot boolean"


@dataclass(frozen=True)
class Rule:
    """span: units of a window. gram: units of an anchor. words: units are words, else bytes. across: only smaller documents count."""

    span: int
    gram: int
    words: bool
    across: bool

    def units(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """One 64-bit code per unit and each document's offsets in units."""
        buf, off = tx.buffers(column)
        if not self.words:
            return tx._CODE[buf], off
        w = tx.Words(buf, off)
        return w.hashes(), w.first


def _prefix(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    sums = np.zeros(len(x) + 1, dtype=np.uint64)
    np.cumsum(x * tx._pow(tx._P, len(x)), out=sums[1:])
    return sums, tx._pow(tx._PINV, len(x) + 1)


def segments(x: np.ndarray, off: np.ndarray, span: int, gram: int) -> tuple[np.ndarray, ...]:
    """(anchor, content, document index, start, windows) of each segment; starts count from the document's start."""
    parts = []
    for at in range(0, max(1, len(x)), PIECE):  # a long text in pieces: a segment cut in two is two contents, settled like any others
        piece = x[at : at + PIECE + span - 1]
        if len(piece) < span:
            continue
        sums, inverse = _prefix(piece)
        m = len(piece) - gram + 1
        h = tx.mix((sums[gram:] - sums[:m]) * inverse[:m], 2)
        low = (h >> U(_POS) << U(_POS)) | np.arange(m, dtype=np.uint64)
        width, have = span - gram + 1, 1
        while have < width:  # sliding minimum by doubling
            step = min(have, width - have)
            low = np.minimum(low[:-step], low[step:])
            have += step
        anchor = (low & U(2**_POS - 1)).astype(np.int64)
        starts = np.arange(len(anchor))
        doc = np.searchsorted(off, starts + at, "right") - 1
        whole = starts + at + span <= off[doc + 1]
        edge = np.ones(len(anchor), bool)
        edge[1:] = (anchor[1:] != anchor[:-1]) | (doc[1:] != doc[:-1]) | (whole[1:] != whole[:-1])
        first = np.flatnonzero(edge)
        last = np.append(first[1:], len(anchor))
        keep = whole[first]
        first, last = first[keep], last[keep]
        ends = last - 1 + span
        g = tx.mix((sums[ends] - sums[first]) * inverse[first] + (ends - first).astype(np.uint64), 7)
        parts.append((h[anchor[first]], g, doc[first], first + at - off[doc[first]], last - first))
    if not parts:
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    return tuple(np.concatenate(c) for c in zip(*parts, strict=True))


def _anchor_rows(rule: Rule, common: np.ndarray) -> Callable:
    """Texts to their segments. common: sorted anchors that are dealt by content as well."""

    def emit(got: list[tuple]) -> pa.RecordBatch:
        h, g, doc, row, s, n = (np.concatenate(c) for c in zip(*got, strict=True))
        both = tx.mix(h, 8) ^ g
        order = np.lexsort((row, s, doc, both))
        first = np.ones(len(order), bool)
        first[1:] = both[order][1:] != both[order][:-1]
        lead = order[np.flatnonzero(first)[np.cumsum(first) - 1]]
        later = doc[order] != doc[lead]
        if not rule.across:  # repeats within the smallest document are settled too
            later |= (s[order] != s[lead]) | (row[order] != row[lead])
        known = np.zeros(len(order), bool)
        known[order[later]] = True
        hot = np.zeros(len(h), bool)
        if len(common):
            hot = common[np.minimum(np.searchsorted(common, h), len(common) - 1)] == h
            h = np.where(hot, tx.mix(both, 15), h)
        h = np.where(known, tx.mix(doc.astype(np.uint64) * U(1 << 20) + s.astype(np.uint64), 9), h)  # nothing to meet: spread
        return pa.RecordBatch.from_arrays([pa.array(tx.signed(h)), pa.array(tx.signed(g)), pa.array(doc), pa.array(row), pa.array(s.astype(np.int32)), pa.array(n.astype(np.int32)), pa.array(known), pa.array(hot)], ["h", "g", "doc", "row", "s", "n", "known", "hot"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got, rows = [], 0
        for b in tx.blocks(batches):
            x, off = rule.units(b.column("text"))
            h, g, doc, s, n = segments(x, off, rule.span, rule.gram)
            if len(h):
                got.append((h, g, tx.ids(b.column("doc"))[doc], tx.ids(b.column("row"))[doc], s, n))
                rows += len(h)
            if rows >= PRE_ROWS:
                yield emit(got)
                got, rows = [], 0
        if got:
            yield emit(got)

    return run


def _contents(rule: Rule) -> Callable:
    """Texts to h, n: anchors and how many different contents they have in some of the texts; once is left out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = []
        for b in tx.blocks(batches):
            h, g, *_ = segments(*rule.units(b.column("text")), rule.span, rule.gram)
            got.append((h, g))
        if got:
            h, g = (np.concatenate(c) for c in zip(*got, strict=True))
            h, n = np.unique(h[np.unique(tx.mix(h, 8) ^ g, return_index=True)[1]], return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(tx.signed(h[n > 1])), pa.array(n[n > 1])], ["h", "n"])

    return run


def common_anchors(base: DataFrame, rule: Rule) -> np.ndarray:
    """Anchors with over SAMPLE_HOT contents in about SAMPLE_ROWS rows, HOT_ANCHORS of them at most, sorted."""
    rows = base.count()
    some = base.select("text") if rows <= SAMPLE_ROWS else base.select("text").sample(SAMPLE_ROWS / rows, seed=7)
    often = some.mapInArrow(_contents(rule), "h long, n long").groupBy("h").agg(F.sum("n").alias("n")).where(F.col("n") > SAMPLE_HOT)
    return np.sort(np.array([r.h for r in often.orderBy(F.desc("n"), "h").limit(HOT_ANCHORS).collect()], np.int64).view(np.uint64))


def merge(start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Disjoint, sorted runs that cover the same units."""
    if not len(start):
        return start, end
    order = np.argsort(start, kind="stable")
    start, reach = start[order], np.maximum.accumulate(end[order])
    first = np.append(True, start[1:] > reach[:-1])
    return start[first], reach[np.append(np.flatnonzero(first)[1:], len(start)) - 1]


def _runs(doc: np.ndarray, row: np.ndarray, start: np.ndarray, end: np.ndarray) -> pa.RecordBatch:
    """Runs of several rows, merged: doc, row, a, b."""
    order = np.lexsort((start, row, doc))
    doc, row, start, end = doc[order], row[order], start[order], end[order]
    if len(doc):
        rank = np.cumsum(np.append(True, (doc[1:] != doc[:-1]) | (row[1:] != row[:-1]))) - 1
        shift = rank * (int(end.max()) + 2)
        a, b = merge(start + shift, end + shift)
        at = np.searchsorted(start + shift, a)
        doc, row, start, end = doc[at], row[at], a - shift[at], b - shift[at]
    return pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(row, pa.int64()), pa.array(start.astype(np.int32)), pa.array(end.astype(np.int32))], ["doc", "row", "a", "b"])


def _cut_out(rule: Rule) -> Callable:
    """Rows with the segments wanted of each to rows h, doc, row, s, n, hot, seg (units as bytes)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in tx.blocks(batches):
            docs, keys, want = tx.ids(b.column("doc")), tx.ids(b.column("row")), b.column("want")
            if rule.words:
                x, off = rule.units(b.column("text"))
                data, width = x.tobytes(), 8
            else:
                x, off = tx.buffers(b.column("text"))
                data, width = x.tobytes(), 1
            counts = np.diff(want.offsets.to_numpy())
            f = [want.flatten().field(i).to_numpy(zero_copy_only=False) for i in range(4)]
            of = np.repeat(np.arange(b.num_rows), counts)
            s, n = f[0].astype(np.int64), f[1].astype(np.int64)
            ok = s + n - 1 + rule.span <= (off[1:] - off[:-1])[of]
            s, n, of, h, hot = s[ok], n[ok], of[ok], f[2][ok], f[3][ok]
            lo = (off[of] + s) * width
            hi = lo + (n - 1 + rule.span) * width
            seg = [data[i:j] for i, j in zip(lo.tolist(), hi.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(h, pa.int64()), pa.array(docs[of]), pa.array(keys[of]), pa.array(s.astype(np.int32)), pa.array(n.astype(np.int32)), pa.array(hot, pa.bool_()), pa.array(seg, pa.binary())], ["h", "doc", "row", "s", "n", "hot", "seg"])

    return run


def _resolved(rule: Rule, resolve: Callable, limit: int = 1 << 20) -> Callable:
    """Rows sorted by h to removed runs; whole groups of h are gathered up to about ``limit`` bytes at a time."""

    def settle(part: pa.Table) -> pa.RecordBatch:
        t = part.combine_chunks()
        seg, off = tx.buffers(t["seg"].combine_chunks())
        if rule.words:
            seg, off = seg.view(np.uint64) if len(seg) % 8 == 0 and seg.ctypes.data % 8 == 0 else np.frombuffer(seg.tobytes(), np.uint64), off // 8
        h, doc, row, s, n = (t[c].to_numpy() for c in ("h", "doc", "row", "s", "n"))
        group = np.cumsum(np.append(True, h[1:] != h[:-1])) - 1
        of, at, size = resolve(group, doc, row, s.astype(np.int64), n.astype(np.int64), seg, off, rule)  # what starts earlier elsewhere
        start = s[of].astype(np.int64) + at
        return _runs(doc[of], row[of], start, start + size)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for b in batches:
            held.append(b)
            size += b.nbytes
            if size < limit:
                continue
            t = pa.Table.from_batches(held)
            h = t["h"].to_numpy()
            change = np.flatnonzero(h[1:] != h[:-1])
            whole = int(change[-1]) + 1 if len(change) else 0
            if whole:  # all but the last group are complete
                yield settle(t.slice(0, whole))
                held = t.slice(whole).combine_chunks().to_batches()
                size = sum(x.nbytes for x in held)
        if held and (t := pa.Table.from_batches(held)).num_rows:
            yield settle(t)

    return run


def _windows(rule: Rule) -> Callable:
    """Segments to one row for each window that may be a first one: w (content hash), doc, row, a, b; and, with a null w, merged
    runs of those that start later than another one of the task."""

    def emit(got: list[tuple]) -> Iterator[pa.RecordBatch]:
        w, doc, row, s = (np.concatenate(c) for c in zip(*got, strict=True))
        order = np.lexsort((row, s, doc, w))
        w, doc, row, s = w[order], doc[order], row[order], s[order]
        head = np.append(True, w[1:] != w[:-1])
        lead = np.flatnonzero(head)[np.cumsum(head) - 1]
        later = doc != doc[lead]
        if not rule.across:
            later |= (s != s[lead]) | (row != row[lead])
        known = _runs(doc[later], row[later], s[later].astype(np.int64), s[later].astype(np.int64) + rule.span)
        yield pa.RecordBatch.from_arrays([pa.nulls(known.num_rows, pa.int64()), *known.columns], ["w", *known.schema.names])
        w, doc, row, s = (x[~later] for x in (w, doc, row, s))
        yield pa.RecordBatch.from_arrays([pa.array(tx.signed(w)), pa.array(doc), pa.array(row), pa.array(s.astype(np.int32)), pa.array((s + rule.span).astype(np.int32))], ["w", "doc", "row", "a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got, rows = [], 0
        for b in tx.blocks(batches, "seg"):
            seg, off = tx.buffers(b.column("seg"))
            x, off = (np.frombuffer(seg.tobytes(), np.uint64), off // 8) if rule.words else (tx._CODE[seg], off)
            n = b.column("n").to_numpy().astype(np.int64)
            of = np.repeat(np.arange(b.num_rows), n)
            at = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            sums, inverse = _prefix(x)
            lo = off[of] + at
            got.append((tx.mix((sums[lo + rule.span] - sums[lo]) * inverse[lo], 10), tx.ids(b.column("doc"))[of], tx.ids(b.column("row"))[of], b.column("s").to_numpy()[of] + at))
            rows += len(of)
            if rows >= PRE_ROWS:
                yield from emit(got)
                got, rows = [], 0
        if got:
            yield from emit(got)

    return run


def _per_row(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Collected runs of each row, merged: doc, row, runs (start, end, start, end ...)."""
    for b in batches:
        lists = []
        for i in range(b.num_rows):
            pairs = b.column("runs")[i].values
            a, e = merge(pairs.field(0).to_numpy().astype(np.int64), pairs.field(1).to_numpy().astype(np.int64))
            lists.append(np.stack([a, e], 1).ravel().astype(np.int32))
        yield pa.RecordBatch.from_arrays([b.column("doc"), b.column("row"), pa.array(lists, pa.list_(pa.int32()))], ["doc", "row", "runs"])


def keyed(docs: DataFrame) -> DataFrame:
    """doc (long, null as the smallest) and text of docs."""
    return docs.select(F.coalesce(docs["doc_id"].cast("long"), F.lit(NULL_ID)).alias("doc"), docs["text"].cast("string").alias("text"))


class Rows:
    """The rows of a table of documents, each known by doc and row: the hash of its text, 0 where no doc_id repeats."""

    def __init__(self, docs: DataFrame):
        self.docs = docs
        repeated = keyed(docs).groupBy("doc").agg(F.count(F.lit(1)).alias("n")).where("n > 1").limit(1).count()
        self.row = F.xxhash64(docs["text"].cast("string")) if repeated else F.lit(0).cast("long")

    def base(self) -> DataFrame:
        return self.docs.select(F.coalesce(self.docs["doc_id"].cast("long"), F.lit(NULL_ID)).alias("doc"), self.row.alias("row"), self.docs["text"].cast("string").alias("text"))

    def with_runs(self, runs: DataFrame, name: str) -> DataFrame:
        """The table with a further column of runs, null where nothing repeats."""
        doc, row = fresh("run_doc", [*self.docs.columns, name]), fresh("run_row", [*self.docs.columns, name])
        side = small(runs.select(F.col("doc").alias(doc), F.col("row").alias(row), F.col("runs").alias(name)), payload=name, width=32, each=4)
        same = (F.coalesce(self.docs["doc_id"].cast("long"), F.lit(NULL_ID)) == side[doc]) & (self.row == side[row])
        return self.docs.join(side, same, "left").drop(doc, row)


def repeated_runs(rows: Rows, rule: Rule, resolve: Callable, hot: int | None = None) -> DataFrame:
    """doc, row, runs: for each row with repeats the merged runs of units, as start, end, start, end ..."""
    base = rows.base()
    hot = HOT if hot is None else hot
    alike = Window.partitionBy("h", "g").orderBy("doc", "s", "row")
    met = base.mapInArrow(_anchor_rows(rule, common_anchors(base, rule)), ANCHORS).repartition("h")  # serves both windows
    first = F.first("doc").over(alike) == F.col("doc") if rule.across else F.rank().over(alike) == 1
    met = met.withColumns({"first": first, "lead": (F.row_number().over(alike) == 1).cast("int")})
    same = Window.partitionBy("h")
    met = met.withColumn("contents", F.sum("lead").over(same))
    met = met.where("known or not first or contents > 1 or hot")
    verdict = cut(met.select("doc", "row", "s", "n", F.when(F.col("first") & ~F.col("known"), F.col("h")).alias("h"), (F.col("hot") | (F.col("contents") > hot)).alias("hot")), "repeats-met", free=True)
    want = verdict.where("h is not null").groupBy("doc", "row").agg(F.collect_list(F.struct("s", "n", "h", "hot")).alias("want"))
    want = cut(want, "repeats-want")
    seg = base.join(want, ["doc", "row"]).mapInArrow(_cut_out(rule), "h long, doc long, row long, s int, n int, hot boolean, seg binary")
    seg = cut(seg, "repeats-segments", free=True)
    plain = seg.where("not hot").repartition("h").sortWithinPartitions("h", "doc", "s").select("h", "doc", "row", "s", "n", "seg")
    runs = plain.mapInArrow(_resolved(rule, resolve), "doc long, row long, a int, b int")
    runs = runs.unionByName(verdict.where("h is null").select("doc", "row", F.col("s").alias("a"), (F.col("s") + F.col("n") + (rule.span - 1)).alias("b")))
    if seg.where("hot").limit(1).count():
        each = cut(seg.where("hot").mapInArrow(_windows(rule), "w long, doc long, row long, a int, b int"), "repeats-windows")
        runs = runs.unionByName(each.where("w is null").drop("w"))
        each = each.where("w is not null")
        least = each.groupBy("w").agg(F.min(F.struct("doc", "a", "row")).alias("low"), F.count(F.lit(1)).alias("times")).where("times > 1")
        later = F.col("low.doc") < F.col("doc") if rule.across else F.col("low") < F.struct("doc", "a", "row")
        runs = runs.unionByName(each.join(least, "w").where(later).select("doc", "row", "a", "b"))
    runs = runs.groupBy("doc", "row").agg(F.collect_list(F.struct("a", "b")).alias("runs")).mapInArrow(_per_row, "doc long, row long, runs array<int>")
    return cut(runs, "repeats-runs", free=True)
