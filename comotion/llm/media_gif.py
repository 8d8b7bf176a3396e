"""GIF columns (operator 10): LZW image data, palettes, disposal, transparency and timed frames.

``decode`` reads any GIF87a or GIF89a byte string: it unpacks the code stream, expands it with the usual growing
dictionary, undoes interlacing, applies the local or global palette, and composes each frame onto the canvas under the
disposal method of the frame before. ``encode`` writes index frames with real LZW compression.

``payload_columns`` stores bytes as pixel indices of grey-scale frames (192 pixels a row, at most ``ROWS`` rows a frame)
and reads them back from the colours that the composed frames show. Defined results: null or empty texts are one padded
block of 192 spaces; equal texts give equal values; long texts span several frames, of which one at a time is composed. Damaged files, and files that claim a canvas or a frame of more than ``MAX_PIXELS``
pixels, raise ``ValueError`` in ``decode`` and give one row of null columns in ``frames``; missing pixels of a code stream
that ends early are index 0.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from comotion.llm.common import doc_text, record, slices

WIDTH, ROWS = 192, 1024
BINS = 8
MAX_PIXELS = 1 << 25  # four bytes each
FRAMES_SCHEMA = "media_id long, frame int, delay_ms int, left int, top int, width int, height int, disposal int, transparent int, rgba binary, histogram array<long>"
COLUMNS_SCHEMA = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_frames int"


@dataclass
class Frame:
    indices: np.ndarray
    left: int = 0
    top: int = 0
    delay_ms: int = 0
    disposal: int = 0
    transparent: int = -1
    palette: np.ndarray | None = None
    rgba: np.ndarray | None = field(default=None, repr=False)


# Code stream -----------------------------------------------------------------------------------------------------


def _widths(n: int, bits: int) -> np.ndarray:
    """Width of the 1st to n-th code after a clear code, as the reader sees it: the table grows by one a code from the second on."""
    size = np.arange(n, dtype=np.int64) + (1 << bits) + 1
    return np.minimum(np.maximum(np.ceil(np.log2(size + 1)).astype(np.int64), bits + 1), 12)


def lzw_codes(data: bytes, bits: int = 8) -> Iterator[list[int]]:
    """Lists of codes, each for a fresh dictionary; a known string is named by its prefix's code and its last byte."""
    first = (1 << bits) + 2
    table: dict[int, int] = {}
    get, free, codes, code = table.get, first, [], -1
    for byte in data:
        if code < 0:
            code = byte
            continue
        known = get(code << 8 | byte)
        if known is not None:
            code = known
            continue
        codes.append(code)
        table[code << 8 | byte] = free
        free += 1
        code = byte
        if free == 4095:
            yield codes
            table.clear()
            free, codes = first, []
    if code >= 0:
        yield [*codes, code]


def lzw_pack(data: bytes, bits: int = 8) -> bytes:
    clear, parts, widths = 1 << bits, [], []
    last = bits + 1
    for codes in lzw_codes(data, bits):
        w = _widths(len(codes), bits)
        parts.append(np.concatenate(([clear], codes)))
        widths.append(np.concatenate(([last], w)))
        last = int(_widths(len(codes) + 1, bits)[-1])
    parts.append(np.array([clear, clear + 1] if not parts else [clear + 1]))
    widths.append(np.array([last] * len(parts[-1])))
    codes, width = np.concatenate(parts).astype(np.uint32), np.concatenate(widths)
    out = bytearray()
    grid = np.arange(12)
    carry = np.zeros(0, np.uint8)
    for k in range(0, len(codes), 1 << 18):
        c, w = codes[k : k + (1 << 18)], width[k : k + (1 << 18)]
        flags = ((c[:, None] >> grid) & 1).astype(np.uint8)[grid < w[:, None]]
        flags = np.concatenate((carry, flags))
        whole = len(flags) // 8 * 8
        out += np.packbits(flags[:whole], bitorder="little").tobytes()
        carry = flags[whole:]
    return bytes(out + np.packbits(carry, bitorder="little").tobytes())


def lzw_unpack(stream: bytes, bits: int, want: int) -> bytes:
    """At most ``want`` indices of a code stream."""
    clear, stop, n_bits = 1 << bits, (1 << bits) + 1, len(stream) * 8
    flags = np.unpackbits(np.frombuffer(stream, np.uint8), bitorder="little")
    base = [bytes((i,)) for i in range(clear)] + [b"", b""]
    full = _widths(4096 - clear - 1, bits)
    ends = np.cumsum(full)
    power = 1 << np.arange(12, dtype=np.int64)
    at, out, got = 0, [], 0
    while at + bits + 1 <= n_bits and got < want:
        # all codes that can follow before the next clear, at the widths a growing table has
        room = int(np.searchsorted(ends, n_bits - at, side="right"))
        w, e = full[:room], at + ends[:room]
        index = (e - w)[:, None] + np.arange(12)
        codes = ((flags[np.minimum(index, n_bits - 1)] * power) * (np.arange(12) < w[:, None])).sum(1) if room else np.zeros(0, np.int64)
        marks = np.flatnonzero((codes == clear) | (codes == stop))
        used = int(marks[0]) if len(marks) else room
        table, begun = list(base), len(out)
        add, show = table.append, out.append
        run = iter(codes[:used].tolist())
        for code in run:  # the first code after a clear is a literal
            before = table[code]
            show(before)
            break
        for code in run:
            try:
                word = table[code]
            except IndexError:
                if code != len(table):
                    raise ValueError("code beyond the table") from None
                word = before + before[:1]
            add(before + word[:1])
            show(word)
            before = word
        got += sum(map(len, out[begun:]))
        if len(marks):
            at = int(e[used])
            if codes[used] == stop:
                break
            continue
        at = int(e[-1]) if room else n_bits
        while at + 12 <= n_bits and got < want:  # a full table stays in use with codes of 12 bits
            code = int((flags[at : at + 12] * power).sum())
            at += 12
            if code in (clear, stop):
                break
            if code >= len(table):
                raise ValueError("code beyond the table")
            word = table[code]
            if len(table) < 4096:
                add(before + word[:1])
            out.append(word)
            before = word
            got += len(word)
        else:
            break
        if code == stop:
            break
    return b"".join(out)[:want]


# Container -------------------------------------------------------------------------------------------------------


def _blocks(data: bytes) -> bytes:
    whole = len(data) // 255 * 255
    head = np.frombuffer(data[:whole], np.uint8).reshape(-1, 255)
    body = np.concatenate((np.full((len(head), 1), 255, np.uint8), head), axis=1).tobytes()
    rest = data[whole:]
    return body + (bytes((len(rest),)) + rest if rest else b"") + b"\0"


def _unblock(data: bytes, at: int) -> tuple[bytes, int]:
    parts = []
    while True:
        if at >= len(data):
            raise ValueError("data ends within a block")
        n = data[at]
        if not n:
            return b"".join(parts), at + 1
        parts.append(data[at + 1 : at + 1 + n])
        at += 1 + n


def _palette(data: bytes, at: int, flags: int) -> tuple[np.ndarray, int]:
    n = 2 << (flags & 7)
    raw = data[at : at + 3 * n]
    if len(raw) < 3 * n:
        raise ValueError("palette ends early")
    return np.frombuffer(raw, np.uint8).reshape(n, 3), at + 3 * n


def _table_bits(palette: np.ndarray) -> int:
    return max(1, int(np.ceil(np.log2(max(2, len(palette)))))) - 1


def encode(frames: list[Frame], width: int, height: int, palette: np.ndarray, interlace: bool = False) -> bytes:
    bits = _table_bits(palette)
    pad = lambda p, b: p.astype(np.uint8).tobytes() + bytes(3 * ((2 << b) - len(p)))
    out = [b"GIF89a", struct.pack("<HHBBB", width, height, 0xF0 | bits, 0, 0), pad(palette, bits)]
    for f in frames:
        flags = f.disposal << 2 | (f.transparent >= 0)
        out.append(b"\x21\xf9\x04" + struct.pack("<BHB", flags, f.delay_ms // 10, max(f.transparent, 0)) + b"\0")
        h, w = f.indices.shape
        own = f.palette
        out.append(b"\x2c" + struct.pack("<HHHHB", f.left, f.top, w, h, (0x80 | _table_bits(own) if own is not None else 0) | 0x40 * interlace))
        if own is not None:
            out.append(pad(own, _table_bits(own)))
        depth = max(2, (_table_bits(own) if own is not None else bits) + 1)
        rows = f.indices[_interlaced(h)] if interlace else f.indices
        out.append(bytes((depth,)) + _blocks(lzw_pack(rows.astype(np.uint8).tobytes(), depth)))
    return b"".join(out) + b"\x3b"


def _interlaced(height: int) -> np.ndarray:
    return np.concatenate([np.arange(start, height, step) for start, step in ((0, 8), (4, 8), (2, 4), (1, 2))])


def decode(data: bytes) -> tuple[int, int, list[Frame]]:
    """Canvas width and height, and the frames with indices and the RGBA canvas that each one shows."""
    frames = list(shown(data))
    return *struct.unpack("<HH", data[6:10]), frames


def shown(data: bytes) -> Iterator[Frame]:
    """The frames one by one, composed."""
    try:
        yield from _shown(data)
    except (IndexError, struct.error) as e:
        raise ValueError("data ends early") from e


def _shown(data: bytes) -> Iterator[Frame]:
    if data[:6] not in (b"GIF87a", b"GIF89a") or len(data) < 13:
        raise ValueError("not a GIF")
    width, height, flags, _, _ = struct.unpack("<HHBBB", data[6:13])
    if width * height > MAX_PIXELS:
        raise ValueError("canvas too large")
    shared, at = _palette(data, 13, flags) if flags & 0x80 else (None, 13)
    canvas = np.zeros((height, width, 4), np.uint8)
    delay, disposal, transparent = 0, 0, -1
    while at < len(data) and data[at] != 0x3B:
        kind = data[at]
        if kind == 0x21:
            label = data[at + 1]
            body, at = _unblock(data, at + 2)
            if label == 0xF9 and len(body) >= 4:
                f, cs, t = struct.unpack("<BHB", body[:4])
                delay, disposal, transparent = cs * 10, f >> 2 & 7, t if f & 1 else -1
            continue
        if kind != 0x2C or at + 10 > len(data):
            raise ValueError("unknown block")
        left, top, w, h, flags = struct.unpack("<HHHHB", data[at + 1 : at + 10])
        if w * h > MAX_PIXELS:
            raise ValueError("frame too large")
        own, at = _palette(data, at + 10, flags) if flags & 0x80 else (None, at + 10)
        bits = data[at]
        stream, at = _unblock(data, at + 1)
        if not 1 < bits < 9:
            raise ValueError("code size out of range")
        raw = lzw_unpack(stream, bits, w * h)
        indices = np.frombuffer(raw.ljust(w * h, b"\0"), np.uint8).reshape(h, w)
        if flags & 0x40:
            undone = np.empty_like(indices)
            undone[_interlaced(h)] = indices
            indices = undone
        frame = Frame(indices, left, top, delay, disposal, transparent, own)
        palette = own if own is not None else shared
        if palette is None:
            raise ValueError("no palette")
        before = canvas.copy() if disposal == 3 else None
        seen = indices[: max(0, height - top), : max(0, width - left)]
        there = canvas[top : top + seen.shape[0], left : left + seen.shape[1]]
        colours = np.zeros((256, 4), np.uint8)
        colours[: len(palette), :3], colours[:, 3] = palette, 255
        if transparent >= 0:
            drawn = seen != transparent
            there[drawn] = colours[seen[drawn]]
        else:
            there[:] = colours[seen]
        frame.rgba = canvas.copy()
        if disposal == 2:
            there[:] = 0
        elif disposal == 3:
            canvas = before
        yield frame
        delay, disposal, transparent = 0, 0, -1


def histogram(rgba: np.ndarray, bins: int = BINS) -> np.ndarray:
    """Counts of opaque pixels by bins of red, green and blue, one after the other."""
    step = 256 // bins
    seen = rgba.reshape(-1, 4)
    if not seen[:, 3].all():
        seen = seen[seen[:, 3] > 0]
    return np.concatenate([np.bincount(seen[:, k], minlength=256).reshape(bins, step).sum(1) for k in range(3)]).astype(np.int64)


# Columns ---------------------------------------------------------------------------------------------------------

GREY = np.repeat(np.arange(256, dtype=np.uint8)[:, None], 3, axis=1)


def payload(raw: bytes) -> bytes:
    return raw.ljust(max(WIDTH, -(-len(raw) // WIDTH) * WIDTH), b" ")


def to_media(data: bytes) -> bytes:
    """A payload as grey frames of ``WIDTH`` pixels a row."""
    rows = np.frombuffer(data, np.uint8).reshape(-1, WIDTH)
    frames = [Frame(rows[k : k + ROWS], delay_ms=100) for k in range(0, len(rows), ROWS)]
    return encode(frames, WIDTH, min(len(rows), ROWS), GREY)


def _stored(raw: bytes) -> tuple:
    media = to_media(payload(raw))
    back, grey, n = [], np.zeros(BINS, np.int64), 0
    for f in shown(media):
        h, w = f.indices.shape
        seen = f.rgba[f.top : f.top + h, f.left : f.left + w]  # a shorter last frame lies on what the one before left
        back.append(seen[:, :, 0].tobytes())
        grey += histogram(seen)[:BINS]  # all three channels are alike
        n += 1
    back = b"".join(back)
    sha = lambda x: hashlib.sha256(x).hexdigest()
    return (len(raw), len(back), sha(back), zlib.crc32(back[-16:]), len(media), sha(media), ",".join(map(str, grey.tolist())), n)


def payload_columns(docs: DataFrame) -> DataFrame:
    """Stores every text as a GIF, reads it back, and returns hashes, sizes and the colour histogram of the frames (grey: one channel)."""
    kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int32())
    out = pa.schema(list(zip([c.split()[0] for c in COLUMNS_SCHEMA.split(", ")], kinds)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            yield record(out, b.column(0), *zip(*(_stored((t or "").encode()) for t in b.column(1).to_pylist())))

    return doc_text(docs).mapInArrow(run, COLUMNS_SCHEMA)


def frames(df: DataFrame, media_id: str | Column, data: str | Column) -> DataFrame:
    """One row for each timed frame of GIF bytes: placement, composed RGBA pixels and colour histogram. Undecodable bytes: one row with null columns."""
    kinds = [pa.int64(), *[pa.int32()] * 8, pa.binary(), pa.list_(pa.int64())]
    out = pa.schema(list(zip([c.split()[0] for c in FRAMES_SCHEMA.split(", ")], kinds)))
    col = lambda c: F.col(c) if isinstance(c, str) else c

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for key, raw in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                try:
                    for _ in shown(raw or b""):  # a file is read whole before its first frame counts
                        pass
                except ValueError:
                    yield record(out, [key], *[[None]] * 10)
                    continue
                for k, f in enumerate(shown(raw or b"")):
                    h, w = f.indices.shape
                    yield record(out, [key], [k], [f.delay_ms], [f.left], [f.top], [w], [h], [f.disposal], [f.transparent], [f.rgba.tobytes()], [histogram(f.rgba)])

    return df.select(col(media_id).cast("long").alias("media_id"), col(data).cast("binary").alias("data")).mapInArrow(run, FRAMES_SCHEMA)
