"""Media columns: Ogg files in binary columns.

``encode`` stores samples as an Ogg file of several logical streams, ``pages`` verifies page checksums, ``demultiplex``
splits the streams, reassembles packets from lacing values (also across pages) and derives timestamps from granule
positions. A broken file gives a row with ``error`` set; it never stops the job.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from blockgraph.llm.text import blocks

RATE = 8000
FRAME = 192
PACKET = FRAME * 20
STREAMS = 2
_PAGE = struct.Struct("<4sBBqIIIB")
_HEAD = struct.Struct("<8sIHHQ")
_MAGIC = b"PCM8mono"
#: Each byte with its bits turned round: Ogg's CRC shifts left, zlib's shifts right, over the same polynomial.
_TURN = bytes(int(f"{b:08b}"[::-1], 2) for b in range(256))


class OggError(ValueError):
    pass


def page_crc(page: bytes) -> int:
    """Ogg's checksum (polynomial 0x04C11DB7, no reflection, zero start, no final xor) by way of zlib's reflected one."""
    x = zlib.crc32(page.translate(_TURN), 0xFFFFFFFF) ^ 0xFFFFFFFF
    return int.from_bytes(x.to_bytes(4, "little").translate(_TURN), "big")


def _page(flags: int, granule: int, serial: int, seq: int, lacing: bytes, body: bytes) -> bytes:
    head = _PAGE.pack(b"OggS", 0, flags, granule, serial, seq, 0, len(lacing)) + lacing
    crc = page_crc(head + body)
    return head[:22] + crc.to_bytes(4, "little") + head[26:] + body


def _stream_pages(packets: list[tuple[bytes, int]], serial: int) -> list[bytes]:
    """Pages of one logical stream: the first packet alone on the first page, later ones packed, and split where a page is full."""
    out, seq = [], 0
    groups = [packets[:1], packets[1:]]
    for g, group in enumerate(groups):
        lacing, body, granule, begun = bytearray(), bytearray(), -1, False
        for data, end in group:
            left = memoryview(data)
            values = b"\xff" * (len(data) // 255) + bytes([len(data) % 255])
            at = 0
            while at < len(values):
                room = 255 - len(lacing)
                if not room:
                    out.append([(1 if begun else 0), granule, seq, bytes(lacing), bytes(body)])
                    seq, begun = seq + 1, at > 0
                    lacing, body, granule = bytearray(), bytearray(), -1
                    continue
                take = values[at : at + room]
                n = sum(take) if take[-1] != 255 else 255 * len(take)
                lacing += take
                body += left[:n]
                left = left[n:]
                at += len(take)
            granule = end
        if lacing:
            out.append([(1 if begun else 0), granule, seq, bytes(lacing), bytes(body)])
            seq += 1
    last = len(out) - 1
    return [_page(f | (2 if i == 0 else 0) | (4 if i == last else 0), g, serial, s, la, b) for i, (f, g, s, la, b) in enumerate(out)]


def encode_samples(payload: bytes, streams: int = STREAMS, packet: int = PACKET) -> bytes:
    """8-bit samples as an Ogg file: packets go to the logical streams in turn, pages of the streams alternate."""
    per: list[list[tuple[bytes, int]]] = [[(_HEAD.pack(_MAGIC, RATE, streams, k, len(payload)), 0)] for k in range(streams)]
    done = [0] * streams
    for i, at in enumerate(range(0, len(payload), packet)):
        part = payload[at : at + packet]
        done[i % streams] += len(part)
        per[i % streams].append((part, done[i % streams]))
    paged = [_stream_pages(p, 0x424C4F00 + k) for k, p in enumerate(per)]
    firsts = [p[0] for p in paged]  # all beginnings come before any data page
    rest = [p[i] for i in range(1, max(map(len, paged))) for p in paged if i < len(p)]
    return b"".join(firsts + rest)


def pages(media: bytes) -> Iterator[tuple[int, int, int, int, bytes, memoryview]]:
    """(flags, granule, serial, sequence, lacing, body) of each page, its checksum verified."""
    at, view = 0, memoryview(media)
    while at < len(media):
        if at + 27 > len(media):
            raise OggError("page header cut off")
        sign, version, flags, granule, serial, seq, crc, n = _PAGE.unpack_from(media, at)
        if sign != b"OggS" or version:
            raise OggError("no page where one is due")
        body_at = at + 27 + n
        lacing = media[at + 27 : body_at]
        to = body_at + sum(lacing)
        if len(lacing) < n or to > len(media):
            raise OggError("page cut off")
        if page_crc(media[at : at + 22] + b"\0\0\0\0" + media[at + 26 : to]) != crc:
            raise OggError(f"checksum of page {seq} of stream {serial}")
        yield flags, granule, serial, seq, lacing, view[body_at:to]
        at = to


def demultiplex(media: bytes) -> dict[int, dict]:
    """For each logical stream its ``packets``, the ``granules`` of pages that end a packet, page count and whether it ended."""
    streams: dict[int, dict] = {}
    for flags, granule, serial, seq, lacing, body in pages(media):
        if flags & 2:
            if serial in streams:
                raise OggError("a stream begins twice")
            streams[serial] = {"packets": [], "granules": [], "pages": 0, "ended": False, "open": None}
        s = streams.get(serial)
        if s is None or s["pages"] != seq or s["ended"]:
            raise OggError("page out of order")
        if bool(flags & 1) != (s["open"] is not None):
            raise OggError("continuation flag does not fit")
        s["pages"] += 1
        part, at, size = s["open"] if s["open"] is not None else b"", 0, 0
        finished = 0
        for v in lacing:
            size += v
            if v < 255:
                s["packets"].append(bytes(part) + bytes(body[at : at + size]))
                part, at, size, finished = b"", at + size, 0, finished + 1
        s["open"] = bytes(part) + bytes(body[at : at + size]) if lacing and lacing[-1] == 255 else None
        if (granule >= 0) != bool(finished):
            raise OggError("granule position does not fit the packets ended")
        if finished:
            s["granules"].append(granule)
        s["ended"] = bool(flags & 4)
    if any(not s["ended"] or s["open"] is not None for s in streams.values()):
        raise OggError("a stream is cut off")
    return streams


def decode_samples(media: bytes) -> tuple[bytes, dict]:
    """Samples back from ``encode_samples`` and what the container says: streams, pages, packets, milliseconds."""
    streams = demultiplex(media)
    if not streams:
        raise OggError("no stream")
    order: dict[int, dict] = {}
    told = set()
    for s in streams.values():
        if not s["packets"] or len(s["packets"][0]) != _HEAD.size:
            raise OggError("no header of samples")
        magic, rate, many, k, total = _HEAD.unpack(s["packets"][0])
        if magic != _MAGIC or not rate:
            raise OggError("unknown stream")
        if k in order:
            raise OggError("two streams of one number")
        order[k] = s
        told.add((rate, many, total))
    if len(told) != 1 or sorted(order) != list(range(many)):
        raise OggError("streams are missing or do not belong together")
    data = [order[k]["packets"][1:] for k in range(many)]
    out = b"".join(p[i] for i in range(max(map(len, data), default=0)) for p in data if i < len(p))
    if len(out) != total or any(s["granules"][-1] != sum(map(len, s["packets"][1:])) for s in order.values()):
        raise OggError("granule positions and samples differ")
    return out, {"streams": len(streams), "pages": sum(s["pages"] for s in streams.values()), "packets": sum(len(s["packets"]) for s in streams.values()), "ms": 1000 * sum(s["granules"][-1] for s in order.values()) // rate}


def pad(raw: bytes, unit: int = FRAME) -> bytes:
    """Blanks up to a positive multiple of the unit."""
    return raw + b" " * ((-len(raw)) % unit if raw else unit)


def _encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in blocks(batches, "text", 4 << 20):
        raw = [(x or "").encode() for x in b.column("text").to_pylist()]
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(map(len, raw), pa.int64()), pa.array([encode_samples(pad(x)) for x in raw], pa.binary())], ["doc_id", "n_bytes", "media"])


def _features(samples: bytes, told: dict) -> str:
    x = np.frombuffer(samples, np.uint8)
    total = int(x.sum(dtype=np.int64))
    level = -(-total // len(x)) if len(x) else 0
    crossings = int(np.count_nonzero(np.diff(x > level)))
    return f"ms={told['ms']};streams={told['streams']};pages={told['pages']};packets={told['packets']};sum={total};peak={int(x.max(initial=0))};crossings={crossings}"


def _decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in blocks(batches, "media", 4 << 20):
        rows: list[tuple] = []
        for media in b.column("media").to_pylist():
            try:
                if media is None:
                    raise OggError("no media")
                samples, told = decode_samples(media)
                rows.append((len(samples), hashlib.sha256(samples).hexdigest(), zlib.crc32(samples[-16:]), len(media), hashlib.sha256(media).hexdigest(), _features(samples, told), None))
            except (OggError, struct.error, IndexError) as e:
                rows.append((None, None, None, None if media is None else len(media), None, None, str(e) or type(e).__name__))
        kinds = (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string())
        names = ["payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "error"]
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("n_bytes"), *(pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds))], ["doc_id", "n_bytes", *names])


def encode(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes and the Ogg file of each whole text (null: empty, stored as one frame of blanks). An empty table gives an empty one.

    Repeated rows give repeated rows with equal files; other columns are left out, whatever their names."""
    return docs.select("doc_id", docs["text"].cast("string").alias("text")).mapInArrow(_encode, "doc_id long, n_bytes long, media binary")


def read(media: DataFrame) -> DataFrame:
    """Checks and features of each Ogg file of a column ``media``; broken, empty or null files give null values and an ``error``.

    An empty table gives an empty one; repeated rows repeat; columns but doc_id, n_bytes and media are left out."""
    return media.select("doc_id", "n_bytes", "media").mapInArrow(_decode, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, error string")
