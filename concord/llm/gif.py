"""Media columns in GIF form.

``decode`` reads GIF87a and GIF89a streams: LZW code streams of any code size (early, deferred and missing
clear codes), global and local palettes, interlacing, transparency, frame times and the disposal rules
(keep, restore background, restore previous). ``frame_table`` turns a column of GIF bytes into timed frames with
colour-histogram columns. ``encode`` writes 8-bit index samples losslessly; ``media_digest`` stores
whole texts as such samples and reads them back.

Defined results: null or empty bytes and bytes without a GIF signature give no frame; a stream that
breaks off gives the frames before the break, and missing samples of a frame are index 0. A canvas or frame beyond
``MAX_AREA``, or a frame that states more than ``MOST_A_BYTE`` samples a byte of its stream (LZW can't hold more), ends decoding with an
error that stands in a row of its own. A null text is stored like an empty one.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql import types as T

from concord.llm.rows import map_text, slices

CLEAR, END, FIRST, FULL = 256, 257, 258, 4096
BYTES = tuple(bytes([i]) for i in range(256))


@dataclass
class Frame:
    left: int
    top: int
    width: int
    height: int
    samples: bytes
    palette: bytes
    delay_cs: int = 0
    disposal: int = 0
    transparent: int | None = None


@dataclass
class Image:
    width: int = 0
    height: int = 0
    background: int = 0
    palette: bytes = b""
    loops: int | None = None
    frames: list[Frame] = field(default_factory=list)
    error: str | None = None


# ---------------------------------------------------------------- LZW, 8-bit samples


def lzw_codes(data: bytes) -> list[list[int]]:
    """Greedy LZW codes of 8-bit samples, one list per dictionary life; each life starts after a clear."""
    lives, codes = [], []
    if not data:
        return [codes]
    table: dict[int, int] = {}
    find, put, free = table.get, codes.append, FIRST
    word = data[0]
    for sample in memoryview(data)[1:]:
        key = word << 8 | sample
        longer = find(key)
        if longer is None:
            put(word)
            word = sample
            if free < FULL:
                table[key] = free
                free += 1
            else:
                lives.append(codes)
                codes = []
                put, free = codes.append, FIRST
                table.clear()
        else:
            word = longer
    put(word)
    lives.append(codes)
    return lives


def _widths(n: int, first: int, start_width: int) -> np.ndarray:
    """Bits of the codes 0..n-1 after a clear: the reader adds an entry with each code but the first."""
    size = first + np.maximum(np.arange(n) - 1, 0)
    width = np.full(n, start_width)
    for w in range(start_width, 12):
        width[size >= 1 << w] = w + 1
    return width


WIDTHS = _widths(FULL, FIRST, 9)


def lzw_pack(lives: list[list[int]]) -> bytes:
    """Codes to little-endian bits: a clear before each life, the end code after the last."""
    flat, widths = [CLEAR], [WIDTHS[:1]]
    for k, codes in enumerate(lives):
        flat += codes
        flat.append(END if k == len(lives) - 1 else CLEAR)
        widths.append(WIDTHS[: len(codes) + 1])
    ends = np.cumsum(np.concatenate(widths))
    at = np.concatenate(([0], ends[:-1]))
    code = np.array(flat, dtype=np.int64) << (at & 7)
    first = at >> 3
    # a code lies in up to three bytes, and no two codes share a bit, so sums put them together
    n = int(ends[-1] + 7) // 8
    packed = np.bincount(first, code & 255, n + 2)
    packed[1:] += np.bincount(first, code >> 8 & 255, n + 1)[: n + 1]
    packed[2:] += np.bincount(first, code >> 16, n)[:n]
    return packed[:n].astype(np.uint8).tobytes()


def lzw_decode(stream: bytes, code_size: int, limit: int) -> bytes:
    """Samples of an LZW stream, at most ``limit`` of them; stops at the end code, at the end of data or at an impossible code."""
    clear, end, first = 1 << code_size, (1 << code_size) + 1, (1 << code_size) + 2
    literals = [*BYTES[:clear], b"", b""]
    full_life = FULL - first + 2
    widths = WIDTHS if code_size == 8 else _widths(FULL, first, code_size + 1)
    raw = np.frombuffer(stream + b"\0\0\0", dtype=np.uint8).astype(np.uint32)
    total, at, out, made = len(stream) * 8, 0, [], 0
    table, prev, used = list(literals), None, 0
    while made < limit:
        # read ahead to where the dictionary must be full, or on at 12 bits while a clear is deferred
        w = widths[used:full_life] if used < full_life else np.full(4096, 12)
        offset = at + np.concatenate(([0], np.cumsum(w)))
        n = int(np.searchsorted(offset, total, side="right")) - 1
        if n <= 0:
            break
        o, w = offset[:n], w[:n]
        i = o >> 3
        codes = ((raw[i] | raw[i + 1] << 8 | raw[i + 2] << 16) >> (o & 7).astype(np.uint32)) & ((1 << w) - 1).astype(np.uint32)
        special = np.flatnonzero((codes == clear) | (codes == end))
        stop = int(special[0]) if len(special) else n
        size = len(table)
        for code in codes[:stop].tolist():
            if prev is None:
                if code >= clear:
                    return b"".join(out)[:limit]
                entry = literals[code]
            elif code < size:
                entry = table[code]
                if size < FULL:
                    table.append(prev + entry[:1])
                    size += 1
            elif code == size and size < FULL:
                entry = prev + prev[:1]
                table.append(entry)
                size += 1
            else:
                return b"".join(out)[:limit]
            out.append(entry)
            prev = entry
            made += len(entry)
        if len(special):
            if codes[stop] == end:
                break
            at = int(offset[stop] + w[stop])
            table, prev, used = list(literals), None, 0
        else:
            at, used = int(offset[n]), used + n
    return b"".join(out)[:limit]


# ---------------------------------------------------------------- container


def _blocks(data: bytes) -> bytes:
    parts = [bytes([len(c := data[i : i + 255])]) + c for i in range(0, len(data), 255)]
    return b"".join(parts) + b"\0"


#: One colour an index: three bits of red, three of green, two of blue.
PALETTE = bytes(v for i in range(256) for v in (i >> 5 << 5, (i >> 2 & 7) << 5, (i & 3) << 6))
#: Canvas and frame areas beyond this are refused, as are frames that state more samples than their stream can hold.
MAX_AREA = 1 << 24
MOST_A_BYTE = 4096


def encode(samples: bytes, width: int = 64, rows_per_frame: int = 64, delay_cs: int = 10) -> bytes:
    """A GIF89a whose frames hold ``samples`` in order, ``width`` to a row, under a palette with one colour an index.

    Frames lie over each other. Their disposal goes through keep, restore background and restore previous, and index 0, the
    padding, is transparent; neither touches the samples.
    """
    step = width * rows_per_frame
    height = min(rows_per_frame, -(-len(samples) // width))
    out = [b"GIF89a", struct.pack("<HHBBB", width, height, 0xF7, 0, 0), PALETTE]
    for k, at in enumerate(range(0, len(samples), step)):
        part = samples[at : at + step]
        out.append(b"\x21\xf9\x04" + struct.pack("<BHB", 1 + k % 3 << 2 | 1, delay_cs, 0) + b"\0")
        out.append(b"\x2c" + struct.pack("<HHHHB", 0, 0, width, -(-len(part) // width), 0) + b"\x08" + _blocks(lzw_pack(lzw_codes(part))))
    return b"".join([*out, b"\x3b"])


def _sub_blocks(data: bytes, at: int) -> tuple[bytes, int]:
    parts = []
    while at < len(data) and (n := data[at]):
        parts.append(data[at + 1 : at + 1 + n])
        at += 1 + n
    return b"".join(parts), at + 1


def _deinterlace(samples: bytes, width: int, height: int) -> bytes:
    order = [*range(0, height, 8), *range(4, height, 8), *range(2, height, 4), *range(1, height, 2)]
    rows = [b""] * height
    for k, row in enumerate(order):
        rows[row] = samples[k * width : (k + 1) * width]
    return b"".join(rows)


def decode(data: bytes | None) -> Image:
    """Parse a GIF into raw index frames with their palettes and graphic-control values."""
    image = Image()
    if not data or data[:6] not in (b"GIF87a", b"GIF89a") or len(data) < 13:
        return image
    image.width, image.height, flags, image.background, _ = struct.unpack_from("<HHBBB", data, 6)
    if image.width * image.height > MAX_AREA:
        image.error = "canvas too large"
        return image
    at = 13
    if flags & 0x80:
        size = 3 << (flags & 7) + 1
        image.palette, at = data[at : at + size], at + size
    delay, disposal, transparent = 0, 0, None
    while at < len(data):
        kind = data[at]
        if kind == 0x21 and at + 1 < len(data):
            label = data[at + 1]
            body, at = _sub_blocks(data, at + 2)
            if label == 0xF9 and len(body) >= 4:
                disposal, delay = body[0] >> 2 & 7, body[1] | body[2] << 8
                transparent = body[3] if body[0] & 1 else None
            elif label == 0xFF and body[:11] == b"NETSCAPE2.0" and len(body) >= 14:
                image.loops = body[12] | body[13] << 8
        elif kind == 0x2C and at + 10 < len(data):
            left, top, width, height, flags = struct.unpack_from("<HHHHB", data, at + 1)
            at += 10
            palette = image.palette
            if flags & 0x80:
                size = 3 << (flags & 7) + 1
                palette, at = data[at : at + size], at + size
            if at >= len(data) or not 2 <= data[at] <= 8:
                break
            stream, after = _sub_blocks(data, at + 1)
            if width * height > min(MAX_AREA, MOST_A_BYTE * (len(stream) + 1)):
                image.error = "frame larger than its stream"
                break
            samples = lzw_decode(stream, data[at], width * height).ljust(width * height, b"\0")
            if flags & 0x40:
                samples = _deinterlace(samples, width, height)
            image.frames.append(Frame(left, top, width, height, samples, palette, delay, disposal, transparent))
            delay, disposal, transparent = 0, 0, None
            at = after
        else:
            break
    return image


def compose(image: Image) -> Iterator[tuple[int, np.ndarray]]:
    """(start time in centiseconds, RGBA canvas) of each frame, after the disposal of those before it."""
    canvas = np.zeros((image.height, image.width), dtype=np.uint32)  # RGBA, four bytes a pixel
    clock = 0
    for f in image.frames:
        before = canvas.copy() if f.disposal == 3 else None
        colours = np.zeros((256, 4), dtype=np.uint8)
        colours[:, 3] = 255
        entries = np.frombuffer(f.palette[: len(f.palette) // 3 * 3], dtype=np.uint8).reshape(-1, 3)
        colours[: len(entries), :3] = entries
        index = np.frombuffer(f.samples, dtype=np.uint8).reshape(f.height, f.width)
        high, wide = min(f.height, max(0, image.height - f.top)), min(f.width, max(0, image.width - f.left))
        index = index[:high, :wide]
        area = canvas[f.top : f.top + high, f.left : f.left + wide]
        shown = True if f.transparent is None else index != f.transparent
        np.copyto(area, colours.view(np.uint32)[:, 0][index], where=shown)
        yield clock, canvas.copy().view(np.uint8).reshape(image.height, image.width, 4)
        clock += f.delay_cs
        if f.disposal == 2:
            area[:] = 0
        elif f.disposal == 3:
            canvas = before


def histogram(canvas: np.ndarray) -> list[int]:
    """Opaque pixels by the two leading bits of each of red, green and blue (64 bins)."""
    key = canvas[..., 0] >> 2 & 48 | canvas[..., 1] >> 4 & 12 | canvas[..., 2] >> 6 | (canvas[..., 3] != 255).view(np.uint8) << 6
    return np.bincount(key.ravel(), minlength=65)[:64].tolist()


FRAMES = "error string, frame int, start_cs long, delay_cs int, disposal int, width int, height int, opaque long, histogram array<long>, rgba binary"


def frame_table(media: DataFrame, id_col: str, gif_col: str) -> DataFrame:
    """Timed, fully composed frames of a column of GIF bytes, one row per frame, and one row with nothing but the error where decoding was refused."""
    out = T.StructType([T.StructField(id_col, media.schema[id_col].dataType), *T.StructType.fromDDL(FRAMES).fields])
    arrow = to_arrow_schema(out)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in slices(batches):
            for key, data in zip(piece.column(0).to_pylist(), piece.column(1).to_pylist(), strict=True):
                image = decode(data)
                for k, (start, canvas) in enumerate(compose(image)):
                    f, bins = image.frames[k], histogram(canvas)
                    row = (key, None, k, start, f.delay_cs, f.disposal, image.width, image.height, sum(bins), bins, canvas.tobytes())
                    yield pa.RecordBatch.from_arrays([pa.array([v], type=t.type) for v, t in zip(row, arrow, strict=True)], schema=arrow)
                if image.error:
                    row = (key, image.error, *[None] * (len(arrow) - 2))
                    yield pa.RecordBatch.from_arrays([pa.array([v], type=t.type) for v, t in zip(row, arrow, strict=True)], schema=arrow)

    return media.select(id_col, gif_col).mapInArrow(run, out)


DIGEST = "n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_frames int, duration_cs long"


def media_digest(docs: DataFrame) -> DataFrame:
    """Store each whole text as the samples of a GIF, read the stored bytes back, and describe both.

    The feature is the colour histogram of the composed frames, through palette, transparency and disposal, summed over the
    frames, 64 bins, comma-joined.
    """

    def start():
        def one(text: str | None) -> tuple:
            body = (text or "").encode()
            gif = encode(body + b"\0" * (-len(body) % 64 or (0 if body else 64)))
            image = decode(gif)
            back = b"".join(f.samples for f in image.frames)
            bins = sum(np.array(histogram(canvas)) for _, canvas in compose(image))
            return (
                len(body), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(gif), hashlib.sha256(gif).hexdigest(),
                ",".join(map(str, bins.tolist())), len(image.frames), sum(f.delay_cs for f in image.frames),
            )

        return one

    return map_text(docs, start, DIGEST)
