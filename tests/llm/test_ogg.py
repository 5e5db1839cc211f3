import hashlib
import random
import zlib

import pytest

from blockgraph.llm import ogg
from tests.llm.data import corpus, frame, odd


def slow_crc(data):
    r = 0
    for b in data:
        r ^= b << 24
        for _ in range(8):
            r = ((r << 1) ^ 0x04C11DB7 if r & 0x80000000 else r << 1) & 0xFFFFFFFF
    return r


def test_checksum_is_ogg_s():
    r = random.Random(1)
    for n in (0, 1, 27, 300):
        data = r.randbytes(n)
        assert ogg.page_crc(data) == slow_crc(data)


@pytest.mark.parametrize("n", [0, 1, 191, 192, 193, 254, 255, 256, 510, 3840, 3841, 65024, 65025, 65026, 200_000])
@pytest.mark.parametrize(("streams", "packet"), [(2, ogg.PACKET), (1, 255), (3, 255 * 300), (2, 7)])
def test_round_trip(n, streams, packet):
    if packet == 7 and n > 4000:
        return
    payload = ogg.pad(random.Random(n).randbytes(n))
    media = ogg.encode_samples(payload, streams, packet)
    back, told = ogg.decode_samples(media)
    assert back == payload and told["streams"] == streams
    every = ogg.demultiplex(media)
    assert sum(s["granules"][-1] for s in every.values()) == len(payload)
    assert all(s["granules"] == sorted(s["granules"]) for s in every.values())


def test_damage_is_found():
    media = ogg.encode_samples(ogg.pad(b"some text " * 3000))
    for at in range(0, len(media), 997):
        broken = bytearray(media)
        broken[at] ^= 4
        with pytest.raises(ogg.OggError):
            ogg.decode_samples(bytes(broken))
    with pytest.raises(ogg.OggError):
        ogg.decode_samples(media[:-1])
    starts = [i for i in range(len(media)) if media.startswith(b"OggS", i)]
    with pytest.raises(ogg.OggError):  # a page is missing
        ogg.decode_samples(media[: starts[2]] + media[starts[3] :])


def test_columns(spark):
    rows = corpus(2, n=60) + odd()
    out = ogg.read(ogg.encode(frame(spark, rows, ("media", "n_bytes")))).collect()
    by = {}
    for r in out:
        by.setdefault(r.doc_id, []).append(r)
    for d, t in rows:
        raw = (t or "").encode()
        p = ogg.pad(raw)
        r = next(r for r in by[d] if r.payload_sha256 == hashlib.sha256(p).hexdigest())
        assert (r.n_bytes, r.payload_bytes, r.tail_crc32, r.error) == (len(raw), len(p), zlib.crc32(p[-16:]), None)
    assert len(out) == len(rows) and len({(r.payload_sha256, r.media_sha256, r.feature) for r in out}) == len({r.payload_sha256 for r in out})
    assert ogg.read(ogg.encode(frame(spark, []))).count() == 0
    def stream(serial, head):
        return b"".join(ogg._stream_pages([(head, 0), (b"a" * 9, 9)], serial))

    head = lambda rate, many, k: ogg._HEAD.pack(ogg._MAGIC, rate, many, k, 9)
    broken = [None, b"OggS", b"x" * 100, b"", stream(1, head(0, 1, 0)), stream(1, head(8000, 2, 0)), stream(1, head(8000, 2, 0)) + stream(2, head(8000, 2, 0)), stream(1, b"short"), stream(1, head(8000, 1, 0))[:-1]]
    bad = ogg.read(spark.createDataFrame([(i, 1, m) for i, m in enumerate(broken)], "doc_id long, n_bytes long, media binary")).collect()
    assert len(bad) == len(broken) and all(r.error and r.payload_sha256 is None for r in bad)
