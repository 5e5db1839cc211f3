"""Token counts of whole texts by a map-side two-tier lookup; no pre-token is ever shuffled.

Tier one is a table of frequent pre-tokens and their token counts, taken from a bounded sample of texts (``SAMPLE_ROWS``
rows, ``SAMPLE_CHARS`` characters of each, ``TABLE_SIZE`` entries; it only saves time, counts never depend on it) and broadcast. Tier two is each Python worker's
own cache, filled by encoding what tier one lacks and emptied at ``CACHE_SIZE`` entries. The vocabulary travels as a
broadcast of its file's text, so executors need no copy of the file.
"""

from __future__ import annotations

import uuid
from collections import Counter
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockgraph.llm.text import blocks, buffers

LIMIT = 512
SAMPLE_ROWS = 800
SAMPLE_CHARS = 8_000
TABLE_SIZE = 40_000
CACHE_SIZE = 400_000
LONGEST_CACHED = 48
#: Fixed value: the pattern by which byte-level BPE splits text before merging.
PRE_TOKEN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
_worker: dict = {}


class Cache(dict):
    """Token counts of pre-tokens: the frequent ones for good, others until the cache is full."""

    def __init__(self, encode: Callable[[str], int], frequent: dict[str, int]):
        super().__init__(frequent)
        self.encode, self.frequent = encode, frequent

    def __missing__(self, piece: str) -> int:
        n = self.encode(piece)
        if len(piece) <= LONGEST_CACHED:
            if len(self) >= CACHE_SIZE + len(self.frequent):
                self.clear()
                self.update(self.frequent)
            self[piece] = n
        return n


class Counting:
    """Counts as the tokenizers library gives them for a byte-level BPE file, added tokens in texts included."""

    def __init__(self, vocabulary: str, frequent: dict[str, int]):
        import json

        import regex
        from tokenizers import Tokenizer

        self.find = regex.compile(PRE_TOKEN).findall
        said = json.loads(vocabulary)
        kind = said["pre_tokenizer"] or {}
        if kind.get("type") != "ByteLevel" or kind.get("add_prefix_space") or said["normalizer"] or any(t["lstrip"] or t["rstrip"] or t["single_word"] for t in said["added_tokens"]):
            raise ValueError("not a plain byte-level BPE vocabulary")
        added = sorted((t["content"] for t in said["added_tokens"]), key=len, reverse=True)
        self.added = regex.compile("|".join(map(regex.escape, added))) if added else None
        tokenizer = Tokenizer.from_str(vocabulary)
        self.cache = Cache(lambda piece: len(tokenizer.encode(piece, add_special_tokens=False).ids), frequent)

    def __call__(self, text: str) -> int:
        if self.added and self.added.search(text):
            parts = self.added.split(text)
            return len(parts) - 1 + sum(self(p) for p in parts if p)
        return sum(map(self.cache.__getitem__, self.find(text)))


def frequent_pieces(texts: list[str]) -> list[str]:
    """The most frequent pre-tokens of a few texts."""
    import regex

    find, seen = regex.compile(PRE_TOKEN).findall, Counter()
    for x in texts:
        seen.update(p for p in find(x) if len(p) <= LONGEST_CACHED)
    return [p for p, _ in seen.most_common(TABLE_SIZE)]


def count_tokens(docs: DataFrame, path: str, limit: int = LIMIT, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit of every whole text (null: empty, no tokens).

    One row out for each row in, repeated ones too; further columns are left out. An empty table gives an empty one."""
    sc = docs.sparkSession.sparkContext
    texts = docs.select("doc_id", docs["text"].cast("string").alias("text"))
    with open(path, encoding="utf-8") as f:
        vocabulary = f.read()
    pieces = frequent_pieces([r[0] for r in texts.select(F.substring("text", 1, SAMPLE_CHARS)).take(sample_rows) if r[0]])
    plain = Counting(vocabulary, {})
    shared, key = sc.broadcast((vocabulary, {p: plain.cache[p] for p in pieces})), uuid.uuid4().hex

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = _worker.get(key)
        if count is None:
            _worker.clear()
            count = _worker[key] = Counting(*shared.value)
        for b in blocks(batches, "text", 4 << 20):
            _, off = buffers(b.column("text"))
            n = np.fromiter((count(x) if x else 0 for x in b.column("text").to_pylist()), np.int64, b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(np.diff(off)), pa.array(n), pa.array(n > limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return texts.mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
