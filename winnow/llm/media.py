"""Media columns: GIF streams decoded into timed frames with colour-histogram columns.

The decoder reads GIF87a and GIF89a: LZW code streams, global and local palettes, interlacing, graphic
control (delay, disposal, transparency), comment and application blocks. Frames are composed on the canvas
as a viewer would. The encoder stores any bytes losslessly as 8-bit samples: 64 samples to a row, up to
1024 rows to a frame, one palette that maps every byte to a colour of its own.

Defined cases: a null text is empty, and an empty payload is one row of 64 zero samples; any id may be
null or repeat; decoding never fails: a stream that ends early or is damaged yields the frames up to there, with samples 0
for what is missing of the last one's codes, and a null stream, one that is no GIF, or one whose canvas or a frame has more than
``MOST_PIXELS`` yields none from there on; a frame that leaves the canvas is cut to it; empty tables give empty results. A text is
handled frame by frame, never as pixels at once.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winnow.llm.common import table

WIDTH, ROWS = 64, 1024
#: A canvas or frame of more pixels counts as damaged, whatever its header says.
MOST_PIXELS = 1 << 25
DELAY_CS = 10  # hundredths of a second that a stored frame stays

_B = np.arange(256)
#: 3 bits of red, 3 of green, 2 of blue, spread over 0 to 255: a colour of its own for every byte.
PALETTE = np.stack([(_B >> 5) * 255 // 7, (_B >> 2 & 7) * 255 // 7, (_B & 3) * 85], axis=1).astype(np.uint8)
_LEVEL = np.zeros(256, np.uint8)
_LEVEL[np.arange(8) * 255 // 7] = np.arange(8)


def lzw_encode(data: bytes, min_bits: int = 8) -> bytes:
    """Codes of growing width, least bit first, with a clear code at the start and whenever the table is full."""
    clear, end = 1 << min_bits, (1 << min_bits) + 1
    codes: list[int] = []
    spans: list[tuple[int, int]] = []  # per table: the codes between two clears
    put = codes.append
    it = iter(data)
    prefix = next(it, -1) << 8
    table: dict[int, int] = {}
    get, next_code, full = table.get, (end + 1) << 8, 4096 << 8
    for c in it:
        k = prefix | c
        known = get(k)
        if known is not None:
            prefix = known
        elif next_code < full:
            put(prefix)
            prefix = c << 8
            table[k] = next_code
            next_code += 256
        else:
            put(prefix)
            prefix = c << 8
            spans.append((len(codes), 1))
            put(clear << 8)
            table = {}
            get, next_code = table.get, (end + 1) << 8
    if prefix >= 0:
        put(prefix)
    put(end << 8)
    ends = [n for n, _ in spans] + [len(codes)]
    runs = np.diff([-1, *ends]) - 1  # codes after each clear, the clear that follows left out
    schedule, _ = code_widths(min_bits, max(int(runs.max(initial=0)) + 1, 1))
    widths = np.concatenate([[min_bits + 1], *(schedule[: n + 1] for n in runs[:-1]), schedule[: runs[-1] + 1 if len(runs) else 0]])
    every = np.concatenate([[clear], np.array(codes, np.int64) >> 8])
    return _pack_codes(every.astype(np.uint64), widths[: len(every)])


_WIDTHS: dict[tuple[int, int], tuple[np.ndarray, np.ndarray]] = {}


def code_widths(min_bits: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Widths of the first n codes after a clear, and the bits before each.

    Before code i, from 1 on, the reader's table has end + 1 + (i - 1) entries.
    """
    size = max(8192, 1 << (n - 1).bit_length())
    if (min_bits, size) not in _WIDTHS:
        known = np.maximum(np.arange(size) - 1, 0) + (1 << min_bits) + 2
        widths = np.clip(np.ceil(np.log2(known + 1)).astype(np.int64), min_bits + 1, 12)
        _WIDTHS[min_bits, size] = widths, np.cumsum(widths) - widths
    widths, before = _WIDTHS[min_bits, size]
    return widths[:n], before[:n]


def _pack_codes(codes: np.ndarray, widths: np.ndarray) -> bytes:
    at = np.cumsum(widths) - widths
    total = int(at[-1] + widths[-1])
    shifted = (codes << (at & 7).astype(np.uint64)).astype(np.uint32)  # at most 12 + 7 bits: three bytes
    first, size = at >> 3, total // 8 + 4
    # bits of neighbouring codes never meet, so bytes can be summed
    out = sum(np.bincount(first + i, (shifted >> np.uint32(8 * i)) & np.uint32(255), size) for i in range(3))
    return out[: (total + 7) // 8].astype(np.uint8).tobytes()


def lzw_decode(data: bytes, min_bits: int, n: int) -> bytes:
    """The first n samples of a code stream; zeros where it ends early.

    After a clear, the width of a code depends only on how many came before it, so the codes up to the next
    clear are cut from the bits in one go.
    """
    clear, end = 1 << min_bits, (1 << min_bits) + 1
    base = [bytes([i]) for i in range(clear)] + [b"", b""]
    bits = np.frombuffer(data + b"\0\0\0\0", np.uint8).astype(np.uint32)
    wide = bits[:-3] | bits[1:-2] << 8 | bits[2:-1] << 16 if len(data) else bits[:0]
    out: list[bytes] = []
    put, made, at, total = out.append, 0, 0, 8 * len(data)
    reach = 5000  # a table is full after 3838 codes; a writer may go on without a clear
    schedule, ahead = code_widths(min_bits, reach)
    table, prev, since = list(base), b"", 0
    while made < n:
        if since + reach > len(schedule):
            schedule, ahead = code_widths(min_bits, since + reach)
        width = schedule[since : since + reach]
        start = at + ahead[since : since + reach] - ahead[since]
        start = start[: np.searchsorted(start + width, total, side="right")]
        if not len(start):
            break
        width = width[: len(start)]
        codes = wide[start >> 3] >> (start & 7).astype(np.uint32) & ((1 << width) - 1).astype(np.uint32)
        stops = np.flatnonzero((codes == clear) | (codes == end))
        take = int(stops[0]) if len(stops) else len(codes)
        broken = False
        grow, room = table.append, 4096 - len(table)
        for code in codes[:take].tolist():
            if not since:
                if code >= clear:
                    broken = True
                    break
                prev = table[code]
                put(prev)
                since = 1
                continue
            since += 1
            if room > 0:
                try:
                    entry = table[code]
                    grow(prev + entry[:1])
                except IndexError:
                    if code != 4096 - room:
                        broken = True
                        break
                    entry = prev + prev[:1]
                    grow(entry)
                room -= 1
            else:
                entry = table[code]
            put(entry)
            prev = entry
        made = sum(map(len, out)) if take < len(codes) or broken else made
        if broken or take < len(codes) and codes[take] == end:
            break
        if take < len(codes):
            at = int(start[take] + width[take])
            table, prev, since = list(base), b"", 0
        else:
            at = int(start[-1] + width[-1])
            made = sum(map(len, out))
    return b"".join(out)[:n].ljust(n, b"\0")


def _sub_blocks(data: bytes) -> bytes:
    return b"".join(bytes([len(data[i : i + 255])]) + data[i : i + 255] for i in range(0, len(data), 255)) + b"\0"


def encode_gif(payload: bytes) -> bytes:
    """Any whole number of rows of samples as a GIF; the payload is the frames' samples one after another."""
    rows = len(payload) // WIDTH
    out = [b"GIF89a", struct.pack("<HHBBB", WIDTH, min(rows, ROWS), 0xF7, 0, 0), PALETTE.tobytes()]
    for top in range(0, rows, ROWS):
        part = payload[top * WIDTH : (top + ROWS) * WIDTH]
        out.append(struct.pack("<BBBBHBB", 0x21, 0xF9, 4, 1 << 2, DELAY_CS, 0, 0))
        out.append(struct.pack("<BHHHHB", 0x2C, 0, 0, WIDTH, len(part) // WIDTH, 0) + b"\x08")
        out.append(_sub_blocks(lzw_encode(part)))
    return b"".join([*out, b"\x3b"])


def decode_gif(media: bytes | None) -> Iterator[dict]:
    """Composed frames in order: number, delay_ms, left, top, width, height and canvas, an array of RGBA rows.

    Disposal 2 clears the frame's rectangle to transparent before the next frame, 3 puts back what was there. Where the
    stream is damaged, it ends.
    """
    try:
        yield from _decoded(media or b"")
    except (ValueError, IndexError, struct.error):  # a field or block beyond the end, or one that can't be
        return


def _decoded(media: bytes) -> Iterator[dict]:
    if media[:3] != b"GIF":
        raise ValueError("not a GIF stream")
    wide, high, flags, _, _ = struct.unpack_from("<HHBBB", media, 6)
    at, shared = 13, None
    if flags & 0x80:
        n = 2 << (flags & 7)
        shared = np.frombuffer(media, np.uint8, 3 * n, at).reshape(n, 3)
        at += 3 * n
    if wide * high > MOST_PIXELS:
        raise ValueError("a canvas beyond the limit")
    canvas = np.zeros((high, wide, 4), np.uint8)
    delay = disposal = number = 0
    clear: int | None = None

    def blocks(i: int) -> tuple[bytes, int]:
        parts = []
        while i < len(media) and media[i]:
            parts.append(media[i + 1 : i + 1 + media[i]])
            i += 1 + media[i]
        return b"".join(parts), i + 1

    while at < len(media) and media[at] != 0x3B:
        if media[at] == 0x21:
            label = media[at + 1]
            body, at = blocks(at + 2)
            if label == 0xF9 and len(body) >= 4:
                packed, delay, index = struct.unpack("<BHB", body[:4])
                disposal, clear = packed >> 2 & 7, index if packed & 1 else None
            continue
        if media[at] != 0x2C:
            break
        left, top, w, h, packed = struct.unpack_from("<HHHHB", media, at + 1)
        at += 10
        palette = shared
        if packed & 0x80:
            n = 2 << (packed & 7)
            palette = np.frombuffer(media, np.uint8, 3 * n, at).reshape(n, 3)
            at += 3 * n
        min_bits = media[at]
        if not 1 <= min_bits <= 8 or w * h > MOST_PIXELS:
            raise ValueError("no frame of a GIF")
        codes, at = blocks(at + 1)
        index = np.frombuffer(lzw_decode(codes, min_bits, w * h), np.uint8).reshape(h, w)
        if packed & 0x40:
            order = np.concatenate([np.arange(s, h, d) for s, d in ((0, 8), (4, 8), (2, 4), (1, 2))])
            straight = np.empty_like(index)
            straight[order] = index
            index = straight
        colours = np.zeros((256, 4), np.uint8)
        if palette is not None:
            colours[: len(palette), :3] = palette
        colours[:, 3] = 255
        box = (slice(min(top, high), min(top + h, high)), slice(min(left, wide), min(left + w, wide)))
        index = index[: box[0].stop - box[0].start, : box[1].stop - box[1].start]
        before = canvas[box].copy() if disposal == 3 else None
        if clear is None:
            canvas[box] = colours[index]
        else:
            seen = index != clear
            canvas[box][seen] = colours[index[seen]]
        yield {"number": number, "delay_ms": 10 * delay, "left": left, "top": top, "width": w, "height": h, "canvas": canvas.copy()}
        if disposal == 2:
            canvas[box] = 0
        elif disposal == 3:
            canvas[box] = before
        number, delay, disposal, clear = number + 1, 0, 0, None


def histogram(rgba: np.ndarray) -> np.ndarray:
    """20 counts of the visible pixels: eighths of red, eighths of green, quarters of blue."""
    seen = rgba[rgba[..., 3] > 0]
    return np.concatenate([np.bincount(seen[:, 0] >> 5, minlength=8), np.bincount(seen[:, 1] >> 5, minlength=8), np.bincount(seen[:, 2] >> 6, minlength=4)])


def samples(frame: dict) -> bytes:
    """The stored bytes of a frame that ``encode_gif`` made, from the colours of its rectangle."""
    t, l = frame["top"], frame["left"]  # noqa: E741
    r, g, b = np.moveaxis(frame["canvas"][t : t + frame["height"], l : l + frame["width"], :3], -1, 0)
    return (_LEVEL[r] << 5 | _LEVEL[g] << 2 | b // 85).astype(np.uint8).tobytes()


def padded(raw: bytes) -> bytes:
    return raw.ljust(max(1, -(-len(raw) // WIDTH)) * WIDTH, b"\0")


def store(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_bytes, media): every text as a GIF column."""

    def encoded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 256):  # an Arrow batch leaves before its media grow large
                part = b.slice(at, 256)
                raw = [x or b"" for x in part.column(1).to_pylist()]
                media = pa.array([encode_gif(padded(x)) for x in raw], pa.binary())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([len(x) for x in raw], pa.int64()), media], names=["id", "n_bytes", "media"])

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").cast("binary").alias("raw")).mapInArrow(
        encoded, "id long, n_bytes long, media binary"
    )


FRAMES = "id long, n_bytes long, media_bytes long, media_sha256 string, number int, start_ms long, delay_ms long, width int, height int, pixels binary, reds array<long>, greens array<long>, blues array<long>"
_KINDS = {"long": pa.int64(), "int": pa.int32(), "string": pa.string(), "binary": pa.binary(), "array<long>": pa.list_(pa.int64())}
#: An Arrow batch of frames leaves when it holds so many bytes of pixels.
BATCH_BYTES = 1 << 22


def _batch(rows: list[tuple], schema: str) -> pa.RecordBatch:
    fields = [x.split() for x in schema.split(", ")]
    cols = zip(*rows, strict=True) if rows else [[]] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(c, _KINDS[k]) for c, (_, k) in zip(cols, fields, strict=True)], names=[n for n, _ in fields])


def frames(stored: DataFrame, as_samples: bool = False) -> DataFrame:
    """One row per timed frame: when it starts and how long it stays, its composed canvas and histogram columns, and its stream's facts.

    Pixels are the RGBA canvas; ``as_samples`` gives the stored bytes of the frame's rectangle instead, for streams of
    ``store``, with the histogram of that rectangle. A stream's frames follow each other in order.
    """

    def decoded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out, held = [], 0
            for i, n, media in zip(*(c.to_pylist() for c in b.columns), strict=True):
                start, facts = 0, (i, n, len(media or b""), hashlib.sha256(media or b"").hexdigest())
                for f in decode_gif(media):
                    t, l = f["top"], f["left"]  # noqa: E741
                    seen = f["canvas"][t : t + f["height"], l : l + f["width"]] if as_samples else f["canvas"]
                    pixels = samples(f) if as_samples else seen.tobytes()
                    x = histogram(seen).tolist()
                    out.append((*facts, f["number"], start, f["delay_ms"], seen.shape[1], seen.shape[0], pixels, x[:8], x[8:16], x[16:]))
                    start, held = start + f["delay_ms"], held + len(pixels)
                    if held >= BATCH_BYTES:
                        yield _batch(out, FRAMES)
                        out, held = [], 0
            if out:
                yield _batch(out, FRAMES)

    return stored.select("id", "n_bytes", "media").mapInArrow(decoded, FRAMES)


MEASURES = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, n_frames long, duration_ms long, feature string"


def measure(stored: DataFrame) -> DataFrame:
    """Reads the payload back from the timed frames of each stored text and sums their histograms.

    The frames of a stream stand together in their partition, frame 0 first, so they are read as they come and nothing is shuffled.
    """

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        facts = None

        def closed() -> tuple:
            i, n, media_bytes, media_sha = facts
            return i, n, size, whole.hexdigest(), zlib.crc32(tail), media_bytes, media_sha, count, shown, ",".join(map(str, hist))

        for b in batches:
            out = []
            for i, n, media_bytes, media_sha, number, delay, pixels, *hues in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if number == 0:
                    if facts is not None:
                        out.append(closed())
                    facts, whole, size, count, shown, hist = (i, n, media_bytes, media_sha), hashlib.sha256(), 0, 0, 0, [0] * 20
                whole.update(pixels)
                size, tail = size + len(pixels), pixels[-64:]
                hist = [x + y for x, y in zip(hist, (v for h in hues for v in h), strict=True)]
                count, shown = count + 1, shown + delay
            if out:
                yield _batch(out, MEASURES)
        if facts is not None:
            yield _batch([closed()], MEASURES)

    timed = frames(stored, as_samples=True)
    return timed.select("id", "n_bytes", "media_bytes", "media_sha256", "number", "delay_ms", "pixels", "reds", "greens", "blues").mapInArrow(rows, MEASURES)


def op3_gif_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measure(store(table(spark, sf_dir, "documents")))
