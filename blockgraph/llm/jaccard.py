"""N-gram Jaccard join: documents whose sets of distinct word shingles have a similarity of at least a threshold.

* Documents with equal sets are one *node* (64-bit fingerprint of the set); the join is over nodes.
* Shingles have one global order, rare first, by a counting sketch of all documents' shingles (2**SKETCH_BITS counters, a
  fixed size; any fixed order gives the right result, the counts only make prefixes selective).
* A node gives its prefix, the first floor((1 - threshold) * n) + 1 shingles in that order, with positions. Two nodes at or
  above the threshold share one of these, so they meet in a *list* (rows of one shingle).
* In lists of at most ``SHORT`` rows all pairs that pass the length filter are formed; pairs are then counted over their
  shared shingles and must pass the positional filter. Longer lists (large groups of near copies) never form all pairs:
  each list's rows are compared with a leader of the list, and only pairs of different components remain; those pass the
  length filter, the triangle inequality of Jaccard distance through the leader (between a lower and an upper bound where
  the distance to the leader is only bounded) and a bitmap filter (sets differ in no fewer
  shingles than their parity bitmaps of 64 * WORDS bits in bits). Lists of the same rows count once, and further leaders are
  taken while very many pairs remain and the last leaders have settled a good part of them. Nothing is dropped: a pair is left out only if a filter rules it out or both are in one component already.
* No list is held by one task: lists of over ``PIECE`` rows are dealt into pieces, what is needed of a whole list (length, leader, components)
  is a grouped aggregate, and pairs of long lists are formed between one piece and those rows of the list whose length band is near.
* A pair is verified once, on whole sets that meet by host node (salted, so a host of very many pairs is spread), after a
  suffix filter (halving both sets at pivots bounds their overlap).
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blockgraph.llm import text as tx
from blockgraph.operators.components import components
from blockgraph.llm.repeats import keyed
from blockgraph.llm.shared import cut, fresh, small
from blockgraph.llm.text import U

SIZE = 5
PERCENT = 80
SKETCH_BITS = 20
CHUNKS = 64
SHORT = 64
SALT = 500
PIECE = 1000
LEADERS = 6
MANY = 250
FEWER = 0.7
WORDS = 8


def sets(column: pa.Array, size: int = SIZE) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of each text, sorted, one after the other, and how many each text has.

    Fewer than ``size`` words: the whole sequence is one shingle; none: an empty set."""
    buf, off = tx.buffers(column)
    w = tx.Words(buf, off)
    h = w.hashes(lower=True)
    g = tx.grams(h, size)
    inside = w.doc[size - 1 :] == w.doc[: len(g)] if len(g) else np.zeros(0, bool)
    doc, g = w.doc[: len(g)][inside], g[inside]
    short = np.flatnonzero((w.count > 0) & (w.count < size))
    if len(short):
        whole = [int(tx.mix(tx.grams(h[w.first[i] : w.first[i + 1]], int(w.count[i])), 30 + int(w.count[i]))[0]) for i in short]
        doc, g = np.concatenate([doc, short]), np.concatenate([g, np.array(whole, np.uint64)])
    order = np.lexsort((g, doc))
    doc, g = doc[order], g[order]
    keep = np.append(True, (g[1:] != g[:-1]) | (doc[1:] != doc[:-1])) if len(g) else np.zeros(0, bool)
    return g[keep], np.bincount(doc[keep], minlength=len(off) - 1).astype(np.int64)


def _sums(x: np.ndarray, n: np.ndarray) -> np.ndarray:
    total = np.zeros(len(x) + 1, np.uint64)
    np.cumsum(x, out=total[1:])
    ends = np.cumsum(n)
    return total[ends] - total[ends - n]


def fingerprints(g: np.ndarray, n: np.ndarray) -> np.ndarray:
    """One 64-bit value for each set."""
    return tx.mix(_sums(tx.mix(g, 20), n) ^ tx.mix(_sums(tx.mix(g, 21), n), 22) ^ n.astype(np.uint64), 23)


def bitmaps(g: np.ndarray, n: np.ndarray) -> np.ndarray:
    """WORDS 64-bit words for each set: the parities of how many of its shingles fall on each bit."""
    bit = (tx.mix(g, 24) % U(64 * WORDS)).astype(np.int64)
    odd = np.bincount(np.repeat(np.arange(len(n)), n) * 64 * WORDS + bit, minlength=len(n) * 64 * WORDS) & 1
    return np.packbits(odd.astype(np.uint8).reshape(-1, 64 * WORDS), axis=1).view(np.int64)


def _describe(size: int) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts, held, rows = np.zeros(2**SKETCH_BITS, np.int64), [], 0
        names, kinds = ["doc", "n", "node", "bits", "chunk", "counts"], [pa.int64(), pa.int32(), pa.int64(), pa.list_(pa.int64()), pa.int32(), pa.binary()]
        for b in tx.blocks(batches):
            g, n = sets(b.column("text"), size)
            held.append((g >> U(64 - SKETCH_BITS)).astype(np.int32))
            rows += len(g)
            if rows > 2**SKETCH_BITS:
                counts += np.bincount(np.concatenate(held), minlength=len(counts))
                held, rows = [], 0
            node = pa.array(tx.signed(fingerprints(g, n)), mask=n == 0)
            yield pa.RecordBatch.from_arrays([pa.array(tx.ids(b.column("doc"))), pa.array(n.astype(np.int32)), node, pa.FixedSizeListArray.from_arrays(pa.array(bitmaps(g, n).ravel()), WORDS).cast(pa.list_(pa.int64())), pa.nulls(len(n), pa.int32()), pa.nulls(len(n), pa.binary())], names)
        if held:
            counts += np.bincount(np.concatenate(held), minlength=len(counts))
        if counts.any():
            parts = [np.minimum(c, 2**31 - 1).astype(np.int32).tobytes() for c in np.split(counts, CHUNKS)]
            yield pa.RecordBatch.from_arrays([*(pa.nulls(CHUNKS, k) for k in kinds[:4]), pa.array(range(CHUNKS), pa.int32()), pa.array(parts, pa.binary())], names)

    return run


def _add_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by chunk to one row for each chunk."""
    at, total = None, None
    out = lambda: pa.RecordBatch.from_arrays([pa.array([at], pa.int32()), pa.array([np.minimum(total, 2**31 - 1).astype(np.int32).tobytes()], pa.binary())], ["chunk", "counts"])
    for b in batches:
        for chunk, counts in zip(b.column("chunk").to_pylist(), b.column("counts"), strict=True):
            x = np.frombuffer(counts.as_buffer(), np.int32).astype(np.int64)
            if chunk != at:
                if at is not None:
                    yield out()
                at, total = chunk, x
            else:
                total = total + x
    if at is not None:
        yield out()


def _prefixes(size: int, percent: int, sketch) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        often = np.frombuffer(sketch.value, np.int32)
        for b in tx.blocks(batches):
            g, n = sets(b.column("text"), size)
            node = fingerprints(g, n)
            mine = tx.signed(node) == b.column("node").to_numpy()
            doc = np.repeat(np.arange(len(n)), n)
            order = np.lexsort((g, often[(g >> U(64 - SKETCH_BITS)).astype(np.int64)], doc))
            position = np.arange(len(g)) - np.repeat(np.cumsum(n) - n, n)
            want = (n - (percent * n + 99) // 100 + 1)[doc]
            use = (position < want) & mine[doc]
            of = doc[use]
            yield pa.RecordBatch.from_arrays([pa.array(tx.signed(g[order][use])), pa.array(tx.signed(node[of])), pa.array(n[of].astype(np.int32)), pa.array(position[use].astype(np.int32))], ["t", "node", "n", "pos"])

    return run


def _ship(size: int) -> Callable:
    """Texts with the hosts their sets are wanted at to rows host, salt, member, node, set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in tx.blocks(batches, limit=1 << 18):
            g, n = sets(b.column("text"), size)
            node = tx.signed(fingerprints(g, n))
            cuts = np.append(0, np.cumsum(n))
            want = b.column("want")
            of = np.repeat(np.arange(b.num_rows), np.diff(want.offsets.to_numpy()))
            host, salt, member = (want.flatten().field(i).to_numpy(zero_copy_only=False) for i in range(3))
            ok = node[of] == b.column("node").to_numpy()[of]
            of, host, salt, member = of[ok], host[ok], salt[ok], member[ok]
            for lo in range(0, len(of), 256):
                part = slice(lo, lo + 256)
                data = [g[cuts[i] : cuts[i + 1]].tobytes() for i in of[part]]
                yield pa.RecordBatch.from_arrays([pa.array(host[part], pa.int64()), pa.array(salt[part], pa.int32()), pa.array(member[part], pa.int32()), pa.array(node[of[part]]), pa.array(data, pa.binary())], ["host", "salt", "member", "node", "set"])

    return run


def overlap_bound(a: np.ndarray, b: np.ndarray, depth: int = 3) -> int:
    """No fewer than the number of equal elements of two sorted sets: both are halved at the middle of the larger one, again and again."""
    if not len(a) or not len(b):
        return 0
    if depth == 0:
        return min(len(a), len(b))
    if len(a) > len(b):
        a, b = b, a
    mid = len(b) // 2
    at = int(np.searchsorted(a, b[mid]))
    return overlap_bound(a[:at], b[:mid], depth - 1) + overlap_bound(a[at:], b[mid:], depth - 1)


def _verify(percent: int) -> Callable:
    """Rows sorted by host, salt, member (the host's own set first) to host, node, both sizes and the overlap.

    A pair that the suffix filter rules out has the bound in place of its overlap, ``exact`` false."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, own = None, None
        for b in batches:
            out = []
            for host, salt, member, node, s in zip(*(b.column(c).to_pylist() for c in ("host", "salt", "member", "node")), b.column("set"), strict=True):
                x = np.frombuffer(s.as_buffer(), np.uint64)
                if not member:
                    key, own = (host, salt), np.array(x)
                elif key == (host, salt) and node != host:
                    total = len(x) + len(own)
                    need = -(-percent * total // (100 + percent))
                    most = overlap_bound(own, x)
                    exact = most >= need
                    if exact:
                        at = np.searchsorted(own, x)
                        at[at == len(own)] = 0
                        most = int(np.count_nonzero(own[at] == x))
                    out.append((host, node, most, total - most, exact, exact and (100 + percent) * most >= percent * total))
            cols = list(zip(*out, strict=True)) if out else [[]] * 6
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.bool_())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["host", "node", "both", "either", "exact", "linked"])

    return run


def pieces(m: str = "m"):
    """Number of pieces of a list of m rows."""
    return F.ceil(F.col(m) / PIECE)


class Join:
    """The join of one table; ``labels`` gives every node's component, ``documents`` every document's."""

    def __init__(self, docs: DataFrame, size: int = SIZE, percent: int = PERCENT):
        self.base, self.size, self.percent = keyed(docs), size, percent
        meta = cut(self.base.mapInArrow(_describe(size), "doc long, n int, node long, bits array<long>, chunk int, counts binary"), "jaccard-meta")
        self.rows = meta.where("chunk is null").select("doc", "n", "node")
        full = meta.where("n > 0").groupBy("node").agg(F.min("doc").alias("doc"), F.first("bits").alias("bits"))
        self.full = cut(full.select("node", "doc", *(F.col("bits")[i].alias(f"bits{i}") for i in range(WORDS))), "jaccard-nodes")
        self.nodes = self.full.select("node", "doc")
        chunks = meta.where("chunk is not null").select("chunk", "counts").repartition("chunk").sortWithinPartitions("chunk")
        counts = dict(chunks.mapInArrow(_add_up, "chunk int, counts binary").collect())  # CHUNKS rows, 2**SKETCH_BITS counters in all
        zero = bytes(2**SKETCH_BITS * 4 // CHUNKS)
        self.sketch = docs.sparkSession.sparkContext.broadcast(b"".join(bytes(counts.get(i, zero)) for i in range(CHUNKS)))

    def lists(self) -> DataFrame:
        """t, node, n, pos, m, piece: prefix rows of shingles that at least two nodes have in their prefixes; m is the list's length.

        Lengths over PIECE come from a grouped count; such lists are dealt by node into pieces before any task sees them whole."""
        rows = self.base.join(small(self.nodes), "doc").mapInArrow(_prefixes(self.size, self.percent, self.sketch), "t long, node long, n int, pos int")
        rows = cut(rows, "jaccard-prefixes")
        hot = cut(rows.groupBy("t").agg(F.count(F.lit(1)).alias("m")).where(F.col("m") > PIECE), "jaccard-hot", free=True)
        rows = rows.join(small(hot), "t", "left").withColumn("piece", F.coalesce(F.pmod(F.xxhash64("node"), pieces()), F.lit(0)).cast("int"))
        rows = rows.withColumn("m", F.coalesce("m", F.count(F.lit(1)).over(Window.partitionBy("t", "piece")))).where("m > 1")
        return cut(rows, "jaccard-lists", free=True)

    @staticmethod
    def of_lists(rows: DataFrame, name: str, keep: str | None = None, **aggregates) -> DataFrame:
        """rows (t, piece, m) with aggregates over each whole list; of lists for which keep does not hold, none."""
        got = rows.groupBy("t").agg(F.first("m").alias("m"), *(a.alias(k) for k, a in aggregates.items()))
        got = cut(got.where(keep) if keep else got, name)
        return rows.join(small(got.select("t", F.explode(F.sequence(F.lit(0), (pieces() - 1).cast("int"))).alias("piece"), *aggregates), width=48), ["t", "piece"])

    def fits(self, a: str, b: str):
        """The length filter."""
        return (F.least(a, b) * 100 >= F.greatest(a, b) * self.percent)

    def short_pairs(self, lists: DataFrame) -> DataFrame:
        """a, b, shared: pairs of short lists that pass the length and positional filters."""
        rows = lists.where(F.col("m") <= SHORT)
        pairs = rows.select("t", F.col("node").alias("a"), F.col("n").alias("na"), F.col("pos").alias("pa")).join(rows.select("t", F.col("node").alias("b"), F.col("n").alias("nb"), F.col("pos").alias("pb")), "t")
        pairs = pairs.where((F.col("a") < F.col("b")) & self.fits("na", "nb")).groupBy("a", "b").agg(
            F.count(F.lit(1)).alias("shared"), F.first("na").alias("na"), F.first("nb").alias("nb"), F.max("pa").alias("pa"), F.max("pb").alias("pb"))
        long = cut(lists.where(F.col("m") > SHORT).groupBy("node").agg(F.count(F.lit(1)).alias("more")), "jaccard-long")
        for side in ("a", "b"):  # shared shingles may also be in long lists
            pairs = pairs.join(small(long.select(F.col("node").alias(side), F.col("more").alias(f"more_{side}"))), side, "left").fillna(0, [f"more_{side}"])
        most = F.col("shared") + F.least("more_a", "more_b") + F.least(F.col("na") - F.col("pa"), F.col("nb") - F.col("pb")) - 1
        return pairs.where(most * (100 + self.percent) >= (F.col("na") + F.col("nb")) * self.percent).select("a", "b", "shared")

    def verified(self, pairs: DataFrame) -> DataFrame:
        """host, node, both, either, exact, linked of distinct pairs (host, node)."""
        pairs = cut(pairs, "jaccard-pairs")
        hosts = pairs.groupBy("host").agg(F.ceil(F.count(F.lit(1)) / SALT).cast("int").alias("salts"))
        members = pairs.join(small(cut(hosts, "jaccard-hosts")), "host").select("node", "host", F.pmod(F.xxhash64("node"), "salts").cast("int").alias("salt"), F.lit(1).alias("member"))
        own = hosts.select(F.col("host").alias("node"), "host", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"), F.lit(0).alias("member"))
        want = members.unionByName(own).groupBy("node").agg(F.collect_list(F.struct("host", "salt", "member")).alias("want"))
        want = cut(want.join(self.nodes, "node"), "jaccard-want")
        sent = self.base.join(small(want, payload="want", width=32, each=32), "doc").mapInArrow(_ship(self.size), "host long, salt int, member int, node long, set binary")
        met = sent.repartition("host", "salt").sortWithinPartitions("host", "salt", "member")
        return cut(met.mapInArrow(_verify(self.percent), "host long, node long, both long, either long, exact boolean, linked boolean").distinct(), "jaccard-verified", free=True)

    def labels(self) -> DataFrame:
        """node, component for each node that is linked with another."""
        lists = self.lists()
        pairs = cut(self.short_pairs(lists), "jaccard-candidates")
        ends = pairs.select(F.col("a").alias("node"), F.struct("shared", "a", "b").alias("p")).unionByName(pairs.select(F.col("b").alias("node"), F.struct("shared", "a", "b").alias("p")))
        best = ends.groupBy("node").agg(F.max("p").alias("p")).select(F.col("p.a").alias("host"), F.col("p.b").alias("node"))
        long = lists.where(F.col("m") > SHORT)
        long = cut(self.of_lists(long, "jaccard-leads", lead=F.min(F.struct("node", "n"))), "jaccard-long-lists")
        led = long.where((F.col("node") != F.col("lead.node")) & self.fits("n", "lead.n")).select(F.col("lead.node").alias("host"), "node")
        done = self.verified(best.unionByName(led).distinct())
        label = components(done.where("linked"), "host", "node")
        apart = self._apart(pairs.select(F.col("a").alias("host"), F.col("b").alias("node")), label, done)
        if long.limit(1).count():
            more, label = self._apart_long(long, label, done)
            apart = apart.unionByName(more)
        rest = self.verified(apart.distinct())
        more = rest.where("linked").select("host", "node")
        if not more.limit(1).count():
            return label
        return components(label.select(F.col("component").alias("host"), "node").unionByName(more), "host", "node")

    @staticmethod
    def _apart(pairs: DataFrame, label: DataFrame, done: DataFrame) -> DataFrame:
        """Pairs of different components that are not verified yet."""
        for side in ("host", "node"):
            pairs = pairs.join(label.select(F.col("node").alias(side), F.col("component").alias(f"c_{side}")), side, "left")
        pairs = pairs.where(F.coalesce("c_host", "host") != F.coalesce("c_node", "node")).select("host", "node")
        seen = done.select("host", "node").unionByName(done.select(F.col("node").alias("host"), F.col("host").alias("node")))
        return pairs.join(seen, ["host", "node"], "left_anti")

    def _apart_long(self, long: DataFrame, label: DataFrame, done: DataFrame) -> tuple[DataFrame, DataFrame]:
        """Pairs of long lists that remain, and the components by then; further leaders are taken while the pairs are many."""
        least = F.lit(1.0) - F.col("both") / F.col("either")  # the distance, or no more than it where the overlap is a bound
        far = done.select(F.col("host").alias("lead_node"), "node", least.alias("near"), F.when(F.col("exact"), least).otherwise(1.0).alias("far"))
        long = long.withColumn("lead_node", F.col("lead.node")).join(far, ["lead_node", "node"], "left")
        own = F.col("node") == F.col("lead_node")
        long = long.select("t", "piece", "m", "node", "n", F.coalesce("near", F.lit(0.0)).alias("near"), F.when(own, 0.0).otherwise(F.coalesce("far", F.lit(1.0))).alias("far"))
        long = cut(long, "jaccard-far")
        same = long.groupBy("t").agg(F.first("m").alias("m"), F.sum(F.xxhash64("node", "near", "far").cast("decimal(38,0)")).alias("s")).groupBy("m", "s").agg(F.min("t").alias("t"))
        same = cut(same.select("t", F.explode(F.sequence(F.lit(0), (pieces() - 1).cast("int"))).alias("piece")), "jaccard-same")
        long = cut(long.join(small(same), ["t", "piece"]), "jaccard-far-once")
        seen, before = done.select("host", "node"), float("inf")
        for turn in range(LEADERS + 1):
            here = long.join(label, "node", "left").withColumn("component", F.coalesce("component", "node"))
            here = cut(self.of_lists(here, "jaccard-ends", "low <> high", low=F.min("component"), high=F.max("component")).drop("low", "high"), "jaccard-open")
            sizes = here.groupBy("t", "component").agg(F.count(F.lit(1)).alias("k")).groupBy("t").agg(F.sum("k").alias("m"), F.sum(F.col("k") * F.col("k")).alias("k2"))
            rows, left = sizes.agg(F.coalesce(F.sum("m"), F.lit(0)), F.coalesce(F.sum(F.col("m") * F.col("m") - F.col("k2")), F.lit(0))).first()
            if left <= 2 * MANY * rows or left > FEWER * before or turn == LEADERS:
                break
            before = left
            led = self.of_lists(here, "jaccard-next-leads", lead=F.min(F.struct(F.xxhash64("node", F.lit(turn)), "node", "n", "component"))).where((F.col("component") != F.col("lead.component")) & self.fits("n", "lead.n"))
            new = led.select(F.col("lead.node").alias("host"), "node").distinct().join(seen, ["host", "node"], "left_anti")
            new = self.verified(new)
            seen = seen.unionByName(new.select("host", "node"))
            label = components(label.select(F.col("component").alias("host"), "node").unionByName(new.where("linked").select("host", "node")), "host", "node")
        marks = [f"bits{i}" for i in range(WORDS)]
        here = cut(here.join(small(self.full.drop("doc"), width=16 + 8 * WORDS), "node"), "jaccard-marked", free=True)
        own = cut(here.groupBy("node").agg(F.collect_set("t").alias("ts")), "jaccard-own-lists")
        here = here.join(small(own, payload="ts"), "node")
        # a is the shorter set of a pair, so b is of the same length band or the next; every piece of a list meets those rows of the whole list
        band = F.floor(F.log("n") / (max(math.log(100 / self.percent), 0.01) * 1.000001))
        here = here.withColumn("band", band)
        a, b = (here.select("t", "piece", "m", "band", *(F.col(c).alias(f"{c}_{k}") for c in ("node", "n", "near", "far", "component", "ts", *marks))) for k in "ab")
        close = F.greatest(F.col("near_a") - F.col("far_b"), F.col("near_b") - F.col("far_a")) <= 1 - self.percent / 100 + 1e-9
        differ = sum((F.bit_count(F.col(f"{m}_a").bitwiseXOR(F.col(f"{m}_b"))) for m in marks), F.lit(0))
        alike = differ * (100 + self.percent) <= (F.col("n_a") + F.col("n_b")) * (100 - self.percent)
        b = b.withColumn("piece", F.explode(F.sequence(F.lit(0), (pieces() - 1).cast("int")))).withColumn("band", F.explode(F.array("band", F.col("band") - 1)))
        rest = a.drop("m").join(b.drop("m"), ["t", "piece", "band"]).where((F.struct("n_a", "node_a") < F.struct("n_b", "node_b")) & (F.col("component_a") != F.col("component_b")) & self.fits("n_a", "n_b") & close & alike)
        rest = rest.where(F.array_min(F.array_intersect("ts_a", "ts_b")) == F.col("t"))  # each pair in the first of its common lists alone
        return rest.select(F.least("node_a", "node_b").alias("host"), F.greatest("node_a", "node_b").alias("node")), label

    def documents(self) -> DataFrame:
        """doc, n, node, component: the smallest doc of the node's component (its own for empty sets)."""
        label = self.labels()
        named = self.nodes.join(label, "node", "left").withColumn("component", F.coalesce("component", "node"))
        least = named.groupBy("component").agg(F.min("doc").alias("low"))
        named = cut(named.join(least, "component").select("node", "low"), "jaccard-components", free=True)
        out = self.rows.join(small(named), "node", "left")
        return out.select("doc", "n", "node", F.coalesce("low", "doc").alias("component"))


def join(docs: DataFrame, size: int = SIZE, percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles, component_id for each row of docs.

    Null and empty texts have empty sets, linked with nothing. A null doc_id counts as the smallest and comes back as null.
    Repeated rows are one node and give equal rows."""
    back = lambda c: F.when(F.col(c) != F.lit(-(2**63)), F.col(c))
    return Join(docs, size, percent).documents().select(back("doc").alias("doc_id"), F.col("n").cast("long").alias("n_shingles"), back("component").alias("component_id"))


def keep_one(docs: DataFrame, size: int = SIZE, percent: int = PERCENT) -> DataFrame:
    """docs without near duplicates: of each component the rows of its smallest doc_id stay, a repeated row once; empty texts stay."""
    found = Join(docs, size, percent)
    key, times = (fresh(c, docs.columns) for c in ("doc_key", "doc_times"))
    stay = found.documents().where("doc = component").groupBy("doc", "node").agg(F.count(F.lit(1)).alias("times"))
    stay = cut(stay.groupBy(F.col("doc").alias(key)).agg(F.max(F.when(F.col("node").isNotNull(), F.col("times")).otherwise(1)).alias(times)), "jaccard-stay")
    kept = docs.join(small(stay), F.coalesce(docs["doc_id"].cast("long"), F.lit(-(2**63))) == F.col(key))
    if stay.where(F.col(times) > 1).limit(1).count():
        again = kept.where(F.col(times) > 1).dropDuplicates(["doc_id", "text"])
        kept = kept.where(F.col(times) == 1).unionByName(again)
    return kept.drop(key, times)
