import hashlib
import random
import struct
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from winnow.llm import media


def read_back(payload):
    return b"".join(media.samples(f) for f in media.decode_gif(media.encode_gif(payload)))


@settings(max_examples=60, deadline=None)
@given(st.binary(max_size=3000))
def test_round_trip(raw):
    payload = media.padded(raw)
    assert len(payload) % 64 == 0 and payload.rstrip(b"\0") == raw.rstrip(b"\0")
    assert read_back(payload) == payload


@pytest.mark.parametrize("size", [64, 4096, 65_536, 65_600, 200_000])
@pytest.mark.parametrize("alphabet", [1, 2, 256])
def test_round_trip_of_large_payloads(size, alphabet):
    rng = random.Random(size)
    payload = media.padded(bytes(rng.randrange(alphabet) for _ in range(size)))
    assert read_back(payload) == payload


def slow_lzw(codes_and_bits):
    """Packs codes, least bit first."""
    acc = n = 0
    for c, b in codes_and_bits:
        acc |= c << n
        n += b
    return acc.to_bytes((n + 7) // 8, "little")


def gif(frames, size=(4, 2), palette=((0, 0, 0), (255, 0, 0), (0, 255, 0), (0, 0, 255)), tail=b"\x3b"):
    """A hand-made stream: frames are (left, top, w, h, indexes, disposal, transparent, delay, interlaced)."""
    out = b"GIF89a" + struct.pack("<HHBBB", *size, 0x81, 0, 0) + bytes(x for c in palette for x in c)
    for left, top, w, h, index, disposal, clear, delay, interlaced in frames:
        out += struct.pack("<BBBBHBB", 0x21, 0xF9, 4, disposal << 2 | (clear is not None), delay, clear or 0, 0)
        out += struct.pack("<BHHHHB", 0x2C, left, top, w, h, 0x40 if interlaced else 0) + b"\x02"
        body = slow_lzw([(4, 3), *(x for i in index for x in ((i, 3), (4, 3))), (5, 3)])  # a clear after every sample
        out += bytes([len(body)]) + body + b"\0"
    return out + tail


def colours(frame):
    names = {(0, 0, 0, 255): "k", (255, 0, 0, 255): "r", (0, 255, 0, 255): "g", (0, 0, 255, 255): "b"}
    return ["".join(names.get(tuple(int(v) for v in p), ".") for p in row) for row in frame["canvas"]]


def test_disposal_and_transparency():
    frames = list(
        media.decode_gif(
            gif([
                (0, 0, 4, 2, [1] * 8, 1, None, 5, False),
                (1, 0, 2, 1, [2, 3], 2, 3, 7, False),  # blue is transparent; the rectangle is cleared afterwards
                (3, 1, 1, 1, [2], 3, None, 9, False),  # put back afterwards
                (0, 1, 1, 1, [0], 0, None, 1, False),
            ])
        )
    )
    assert [colours(f) for f in frames] == [["rrrr", "rrrr"], ["rgrr", "rrrr"], ["r..r", "rrrg"], ["r..r", "krrr"]]
    assert [f["delay_ms"] for f in frames] == [50, 70, 90, 10]


def test_interlaced_rows():
    rows = [0, 1, 2, 3, 0, 1, 2, 3, 1]
    order = [0, 8, 4, 2, 6, 1, 3, 5, 7]
    f = next(media.decode_gif(gif([(0, 0, 1, 9, [rows[i] for i in order], 1, None, 0, True)], size=(1, 9))))
    assert "".join(colours(f)) == "".join("krgb"[i] for i in rows)


def test_a_stream_cut_short_gives_zeros():
    whole = media.lzw_encode(b"abcabcabc" * 20)
    assert media.lzw_decode(whole, 8, 180) == b"abcabcabc" * 20
    cut = media.lzw_decode(whole[: len(whole) // 2], 8, 180)
    assert len(cut) == 180 and (b"abcabcabc" * 20).startswith(cut.rstrip(b"\0"))
    assert media.lzw_decode(b"", 8, 5) == b"\0" * 5


def whole_frames(stream):
    out = []
    for f in media.decode_gif(stream):
        assert f["canvas"].shape[2] == 4
        out.append(f)
    return out


def test_every_prefix_decodes_without_failing():
    payload = media.padded(bytes(random.Random(1).randrange(256) for _ in range(70_000)))
    for stream in (media.encode_gif(media.padded(b"abc" * 100)), gif([(0, 0, 4, 2, [1] * 8, 1, None, 5, False), (1, 0, 2, 1, [2, 3], 2, 3, 7, True)])):
        n = len(whole_frames(stream))
        for at in range(len(stream)):
            assert len(whole_frames(stream[:at])) <= n
    stream = media.encode_gif(payload)
    whole = whole_frames(stream)
    assert len(whole) == 2
    for at in random.Random(2).sample(range(len(stream)), 25):
        for f, g in zip(whole_frames(stream[:at])[:-1], whole, strict=False):
            assert (f["canvas"] == g["canvas"]).all()  # frames before the broken one are whole
    assert whole_frames(None) == whole_frames(b"") == whole_frames(b"PNG" * 9) == []


def test_damaged_bytes_decode_without_failing():
    rng = random.Random(3)
    base = [media.encode_gif(media.padded(b"some text " * 30)), gif([(0, 0, 4, 2, [1] * 8, 1, None, 5, False), (3, 1, 1, 1, [2], 3, None, 9, False)])]
    for k in range(600):
        stream = bytearray(base[k % 2])
        for _ in range(rng.randint(1, 6)):
            stream[rng.randrange(len(stream))] = rng.randrange(256)
        whole_frames(bytes(stream))
    wide = bytearray(base[0])
    wide[6:10] = b"\xff\xff\xff\xff"
    assert whole_frames(bytes(wide)) == []


def test_damaged_streams_in_a_table(spark):
    good = media.encode_gif(media.padded(b"text"))
    rows = spark.createDataFrame([(1, 4, bytearray(good)), (2, 4, bytearray(good[:20])), (3, 0, None), (4, 4, bytearray(b"no gif"))], "id long, n_bytes long, media binary")
    assert [r.id for r in media.frames(rows).collect()] == [1] and [r.doc_id for r in media.measure(rows).collect()] == [1]


def test_long_codes_across_a_full_table():
    data = bytes(random.Random(5).randrange(256) for _ in range(60_000))
    assert media.lzw_decode(media.lzw_encode(data), 8, len(data)) == data


def test_measures_of_odd_rows(spark):
    texts = [None, "", "x", "é" * 40, "a" * 100_000, "a" * 100_000]
    docs = spark.createDataFrame([(i if i != 3 else None, t, "z") for i, t in enumerate(texts)], "doc_id long, text string, media string")
    got = {r.n_bytes: r for r in media.measure(media.store(docs)).collect()}
    for t in texts:
        raw = (t or "").encode()
        payload = raw.ljust(max(64, -(-len(raw) // 64) * 64), b"\0")
        r = got[len(raw)]
        assert (r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
        assert sum(map(int, r.feature.split(",")[:8])) == len(payload)
    assert media.measure(media.store(docs.limit(0))).count() == 0
    frames = media.frames(media.store(docs.where("length(text) > 1000").limit(1))).collect()
    assert [f.number for f in frames] == [0, 1] and frames[1].start_ms == frames[0].delay_ms == 100
    assert np.frombuffer(frames[0].pixels, np.uint8).size == frames[0].width * frames[0].height * 4


def test_whole_table(spark, sf):
    texts = {r.doc_id: (r.text or "").encode() for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    rows = media.op3_gif_media(spark, sf).collect()
    assert len(rows) == len(texts)
    for r in rows:
        payload = media.padded(texts[r.doc_id])
        assert r.payload_sha256 == hashlib.sha256(payload).hexdigest() and r.media_sha256 == hashlib.sha256(media.encode_gif(payload)).hexdigest()
