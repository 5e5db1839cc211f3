"""Vectorised text kernels over Arrow string columns: no Python object is made per word or per byte.

A block of documents is one byte buffer with offsets (null text: empty). Words are maximal runs of bytes other than
0x20 and 0x09-0x0D; UTF-8 continuation bytes are never separators, so working on bytes equals working on characters.
Hashes are 64 bits wide: polynomial over random byte codes, then a finaliser.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
_SEP = np.zeros(256, dtype=bool)
_SEP[[0x20, *range(0x09, 0x0E)]] = True
_rng = np.random.default_rng(20240611)
_CODE = _rng.integers(1, 2**63, 256, dtype=np.uint64) * U(2) + U(1)
_LOWER = np.arange(256)
_LOWER[65:91] += 32
_CODE_LOWER = _CODE[_LOWER]
_P = U(0x9E3779B97F4A7C15 | 1)
_PINV = U(pow(int(_P), -1, 2**64))
_Q = U(0xD1342543DE82EF95)
_powers: dict[int, np.ndarray] = {}


def _pow(base: np.uint64, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64, kept between calls."""
    have = _powers.get(int(base))
    if have is None or len(have) < n:
        size = max(n, 1 << 16)
        have = np.full(size, base, dtype=np.uint64)
        have[0] = 1
        np.multiply.accumulate(have, out=have)
        if size <= 1 << 23:
            _powers[int(base)] = have
    return have[:n]


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """A bijective finaliser of 64-bit values; salt gives independent ones."""
    x = x + U((0x9E3779B97F4A7C15 * (2 * salt + 1)) % 2**64)
    x ^= x >> U(30)
    x *= U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets (len + 1) of a string or binary column; a null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offs, data = column.buffers()
    if len(column) == 0 or offs is None:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    off = np.frombuffer(offs, dtype=np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    buf = np.frombuffer(data, dtype=np.uint8)[off[0] : off[-1]] if data is not None else np.zeros(0, np.uint8)
    return buf, off - off[0]


def blocks(batches: Iterator[pa.RecordBatch], column: str = "text", limit: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """Cuts record batches so that each holds at most about ``limit`` bytes of the column (one longer text stays whole)."""
    for batch in batches:
        _, off = buffers(batch.column(column))
        at = 0
        while at < batch.num_rows:
            to = max(at + 1, int(np.searchsorted(off, off[at] + limit, "right")) - 1)
            yield batch.slice(at, to - at)
            at = to


def ids(column: pa.Array) -> np.ndarray:
    """An integer column as int64; null is the smallest value."""
    return column.cast(pa.int64()).fill_null(-(2**63)).to_numpy(zero_copy_only=False)


class Words:
    """Words of a block of texts: ``start``/``end`` byte positions, ``doc`` index, ``first`` (offsets of each document's words)."""

    def __init__(self, buf: np.ndarray, off: np.ndarray):
        self.buf, self.off = buf, off
        inside = ~_SEP[buf]
        edge = np.zeros(len(buf) + 1, dtype=bool)
        edge[off] = True
        before = np.zeros(len(buf), dtype=bool)
        before[1:] = inside[:-1]
        before &= ~edge[:-1]
        self.start = np.flatnonzero(inside & ~before)
        after = np.zeros(len(buf), dtype=bool)
        after[:-1] = inside[1:]
        after &= ~edge[1:]
        self.end = np.flatnonzero(inside & ~after) + 1
        self.first = np.searchsorted(self.start, off)
        self.count = np.diff(self.first)
        self.doc = np.repeat(np.arange(len(off) - 1), self.count)

    def hashes(self, lower: bool = False, piece: int = 4 << 20) -> np.ndarray:
        """One 64-bit hash for each word; ``lower`` maps A-Z to a-z first. Worked out in pieces of whole words, so that a very long text
        needs no arrays of its length."""
        code, out = _CODE_LOWER if lower else _CODE, np.empty(len(self.start), np.uint64)
        at = 0
        while at < len(out):
            lo = self.start[at]
            to = max(at + 1, int(np.searchsorted(self.end, lo + piece, "right")))
            m = int(self.end[to - 1] - lo)
            sums = np.zeros(m + 1, dtype=np.uint64)
            np.cumsum(code[self.buf[lo : lo + m]] * _pow(_P, m), out=sums[1:])
            start = self.start[at:to] - lo
            out[at:to] = mix((sums[self.end[at:to] - lo] - sums[start]) * _pow(_PINV, m + 1)[start])
            at = to
        return out


def grams(units: np.ndarray, n: int) -> np.ndarray:
    """Hashes of every n consecutive units; those across documents are the caller's to leave out."""
    if len(units) < n:
        return np.zeros(0, np.uint64)
    q = _pow(_Q, n)
    m = len(units) - n + 1
    out = units[:m].copy()
    for k in range(1, n):
        out += units[k : k + m] * q[k]
    return mix(out, 1)


def signed(x: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(x).view(np.int64)
