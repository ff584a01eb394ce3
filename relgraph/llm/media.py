"""GIF media columns: LZW code streams, palettes, disposal, transparency, timed frames, colour histograms.

`decode_frames` turns a column of GIF files into one row a frame, composed on the logical screen.
`store_text` keeps any bytes losslessly as 8-bit samples of a GIF, `read_back` gets them again, and composes the
frames with the palette, times, disposal and transparency that the file holds.

Null or damaged files give one row with `error` set and no frame; null or empty texts are stored as one row of blanks.
Very long texts become many frames and are worked on one text at a time. Repeated rows are each returned, equal
texts with equal values; there are no ties. Empty tables give empty results; other columns of the input are left out, so
clashing names cannot occur.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relgraph.llm.common import slices, texts

WIDTH, ROWS, DELAY_CS = 192, 256, 10
MOST_CODES, FULL = 4096, 4095
FRAME_SCHEMA = (
    "id long, frame int, start_ms long, delay_ms long, disposal int, transparent int, "
    "width int, height int, rgb binary, histogram array<int>, error string"
)
TEXT_SCHEMA = (
    "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, "
    "media_bytes long, media_sha256 string, feature string, "
    "frames array<struct<start_ms: long, delay_ms: long, disposal: int, transparent: int, histogram: array<int>>>"
)

FRAMES = pa.list_(pa.struct([("start_ms", pa.int64()), ("delay_ms", pa.int64()), ("disposal", pa.int32()), ("transparent", pa.int32()), ("histogram", pa.list_(pa.int32()))]))


@dataclass
class Frame:
    left: int
    top: int
    index: np.ndarray
    palette: np.ndarray
    delay_cs: int = 0
    disposal: int = 0
    transparent: int = -1


def cube() -> np.ndarray:
    """A palette of 8 reds, 8 greens and 4 blues: sample value = red * 32 + green * 4 + blue."""
    v = np.arange(256)
    return np.stack([(v >> 5) * 255 // 7, (v >> 2 & 7) * 255 // 7, (v & 3) * 85], 1).astype(np.uint8)


def _widths(n: int, least: int) -> np.ndarray:
    """Bits of the n codes that follow a clear code, for a first width of `least`."""
    known = (1 << (least - 1)) + 1 + np.arange(n)
    return np.minimum(12, np.maximum(least, np.floor(np.log2(np.maximum(known, 1))).astype(np.int64) + 1))


def lzw_pack(data: bytes, depth: int = 8) -> bytes:
    """LZW code stream of 8-bit samples (or fewer bits), least significant bit first."""
    clear, least = 1 << depth, depth + 1
    codes: list[int] = []
    borders = [0]
    known: dict[tuple[int, int], int] = {}
    put, fresh = codes.append, clear + 2
    if data:
        prefix = data[0]
        for sample in data[1:]:
            pair = prefix, sample
            if pair in known:
                prefix = known[pair]
                continue
            put(prefix)
            if fresh == FULL:
                put(clear)
                borders.append(len(codes))
                known.clear()
                fresh = clear + 2
            else:
                known[pair] = fresh
                fresh += 1
            prefix = sample
        put(prefix)
    put(clear + 1)
    n = len(codes)
    bits = np.concatenate([_widths(b - a, least) for a, b in zip(borders, [*borders[1:], n], strict=True)])
    value = np.concatenate([[clear], np.array(codes, np.int64)])
    bits = np.concatenate([[least], bits])
    start = np.cumsum(bits) - bits
    value = value << (start & 7)
    size = int(start[-1] + bits[-1] + 7) // 8
    out = np.zeros(size + 3)
    for k in range(3):
        out += np.bincount((start >> 3) + k, value >> 8 * k & 255, size + 3)
    return out[:size].astype(np.uint8).tobytes()


def _entries(codes: list[int], known: list[bytes], parts: list[bytes], prev: bytes) -> bytes:
    """Append each code's entry to the parts, and what it teaches to the table while there is room; the last entry."""
    if codes and not prev:
        if codes[0] >= len(known):
            raise ValueError("code beyond the table")
        prev = known[codes[0]]
        parts.append(prev)
        codes = codes[1:]
    add, emit = known.append, parts.append
    room = MOST_CODES - len(known)
    for code in codes[:room]:
        if code < len(known):
            entry = known[code]
            add(prev + entry[:1])
        else:
            if code > len(known):
                raise ValueError("code beyond the table")
            entry = prev + prev[:1]
            add(entry)
        emit(entry)
        prev = entry
    if len(codes) > room:
        parts += [known[code] for code in codes[room:]]
        prev = parts[-1]
    return prev


def lzw_unpack(stream: bytes, depth: int, expected: int) -> bytes:
    """Samples of a code stream: stops at the end code, at the expected length, or when codes run out."""
    clear, least = 1 << depth, depth + 1
    raw = np.frombuffer(stream + b"\0\0\0", np.uint8).astype(np.int64)
    total, at, had = 8 * len(stream), 0, 0
    first = [bytes([i]) for i in range(clear)] + [b"", b""]
    parts: list[bytes] = []
    known, prev, read = first.copy(), b"", 0  # read: codes since the last clear code, which may be far back
    while had < expected and at + least <= total:
        n = min((total - at) // least, MOST_CODES + 2)
        bits = _widths(read + n, least)[read:] if read < MOST_CODES else np.full(n, MOST_CODES.bit_length() - 1)
        start = at + np.cumsum(bits) - bits
        start = start[start + bits <= total]
        bits = bits[: len(start)]
        if not len(start):
            break
        j = start >> 3
        codes = (raw[j] | raw[j + 1] << 8 | raw[j + 2] << 16) >> (start & 7) & ((1 << bits) - 1)
        stop = np.flatnonzero((codes == clear) | (codes == clear + 1))
        last = int(stop[0]) if len(stop) else len(codes)
        seen = len(parts)
        prev = _entries(codes[:last].tolist(), known, parts, prev)
        had += sum(map(len, parts[seen:]))
        if len(stop):
            if codes[last] == clear + 1:
                break
            at = int(start[last] + bits[last])
            known, prev, read = first.copy(), b"", 0
        else:
            at = int(start[-1] + bits[-1])
            read += len(codes)
    found = b"".join(parts)[:expected]
    if len(found) < expected:
        raise ValueError("code stream ends early")
    return found


def encode(frames: list[Frame], width: int, height: int, palette: np.ndarray) -> bytes:
    """A GIF of the frames, whose samples are indices into the 256-entry palette."""
    out = [b"GIF89a", struct.pack("<HHBBB", width, height, 0xF7, 0, 0), palette.astype(np.uint8).tobytes()]
    for f in frames:
        h, w = f.index.shape
        flags = f.disposal << 2 | (f.transparent >= 0)
        out.append(struct.pack("<BBBBHBB", 0x21, 0xF9, 4, flags, f.delay_cs, max(f.transparent, 0), 0))
        out.append(struct.pack("<BHHHHBB", 0x2C, f.left, f.top, w, h, 0, 8))
        packed = lzw_pack(f.index.astype(np.uint8).tobytes())
        out += [bytes([len(part := packed[i : i + 255])]) + part for i in range(0, len(packed), 255)]
        out.append(b"\0")
    return b"".join([*out, b";"])


def _blocks(raw: bytes, at: int) -> tuple[bytes, int]:
    parts = []
    while size := raw[at]:
        parts.append(raw[at + 1 : at + 1 + size])
        at += 1 + size
    return b"".join(parts), at + 1


def _interlaced(height: int) -> np.ndarray:
    """Row order of an interlaced image: every eighth from 0 and 4, every fourth from 2, every second from 1."""
    return np.concatenate([np.arange(a, height, s) for a, s in ((0, 8), (4, 8), (2, 4), (1, 2))])


def parse(raw: bytes) -> tuple[int, int, int, list[Frame]]:
    """Screen width, height, background index and the frames as stored; ValueError if it is no GIF."""
    if raw[:6] not in (b"GIF87a", b"GIF89a"):
        raise ValueError("no GIF signature")
    try:
        width, height, flags, background, _ = struct.unpack_from("<HHBBB", raw, 6)
        at, shared = 13, None
        if flags & 0x80:
            size = 3 << (flags & 7) + 1
            shared = np.frombuffer(raw, np.uint8, size, at).reshape(-1, 3)
            at += size
        frames, delay, disposal, transparent = [], 0, 0, -1
        while raw[at] != 0x3B:
            if raw[at] == 0x21:
                body, after = _blocks(raw, at + 2)
                if raw[at + 1] == 0xF9:
                    packed, delay, index = struct.unpack_from("<BHB", body)
                    disposal, transparent = packed >> 2 & 7, index if packed & 1 else -1
                at = after
            elif raw[at] == 0x2C:
                left, top, w, h, packed = struct.unpack_from("<HHHHB", raw, at + 1)
                at += 10
                palette = shared
                if packed & 0x80:
                    size = 3 << (packed & 7) + 1
                    palette = np.frombuffer(raw, np.uint8, size, at).reshape(-1, 3)
                    at += size
                if palette is None:
                    raise ValueError("no palette")
                depth = raw[at]
                if not 1 <= depth <= 8:
                    raise ValueError("code size outside 1 to 8")
                stream, at = _blocks(raw, at + 1)
                index = np.frombuffer(lzw_unpack(stream, depth, w * h), np.uint8).reshape(h, w)
                if packed & 0x40:
                    rows = np.empty_like(index)
                    rows[_interlaced(h)] = index
                    index = rows
                frames.append(Frame(left, top, index, palette, delay, disposal, transparent))
                delay, disposal, transparent = 0, 0, -1
            else:
                raise ValueError("unknown block")
    except (IndexError, struct.error) as e:
        raise ValueError("file ends early") from e
    return width, height, background, frames


def histogram(rgb: np.ndarray) -> np.ndarray:
    """Pixels in each of 64 colours: two high bits of red, green and blue."""
    top = rgb >> 6
    return np.bincount((top[..., 0] << 4 | top[..., 1] << 2 | top[..., 2]).ravel(), minlength=64)


def compose(raw: bytes) -> Iterator[tuple[Frame, np.ndarray]]:
    """Each frame of a file with the screen as shown."""
    width, height, _, frames = parse(raw)
    return shown(width, height, frames)


def shown(width: int, height: int, frames: list[Frame]) -> Iterator[tuple[Frame, np.ndarray]]:
    """Each frame with the screen: transparent samples keep what lies below; after its time a frame
    stays, is cleared to the background (black, as viewers show it) or gives way to what was there before."""
    screen = np.zeros((height, width, 3), np.uint8)
    for f in frames:
        before = screen.copy() if f.disposal == 3 else None
        h, w = min(f.index.shape[0], height - f.top), min(f.index.shape[1], width - f.left)
        if h > 0 and w > 0:
            index = f.index[:h, :w]
            if int(index.max()) >= len(f.palette):
                raise ValueError("sample beyond the palette")
            box, colours = screen[f.top : f.top + h, f.left : f.left + w], f.palette[index]
            if f.transparent < 0:
                box[:] = colours
            else:
                np.copyto(box, colours, where=(index != f.transparent)[..., None])
        yield f, screen.copy()
        if f.disposal == 2 and h > 0 and w > 0:
            screen[f.top : f.top + h, f.left : f.left + w] = 0
        elif before is not None:
            screen = before


def decode_frames(df: DataFrame, media: str, key: str) -> DataFrame:
    """One row a frame of each GIF in binary column `media`, in order, with its start time and histogram.

    A null or damaged file gives one row with `error`; a file without frames gives none.
    """

    def run(batches):
        for batch in batches:
            rows = []
            for k, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                try:
                    if raw is None:
                        raise ValueError("null")
                    began, own = 0, []
                    for n, (f, rgb) in enumerate(compose(raw)):
                        h, w = rgb.shape[:2]
                        own.append((k, n, began, f.delay_cs * 10, f.disposal, f.transparent, w, h, rgb.tobytes(), histogram(rgb).tolist(), None))
                        began += f.delay_cs * 10
                    rows += own
                except ValueError as e:
                    rows.append((k, *[None] * 9, str(e)))
                if len(rows) > 64:
                    yield _rows(rows)
                    rows = []
            if rows:
                yield _rows(rows)

    def _rows(rows):
        names = [x.split()[0] for x in FRAME_SCHEMA.split(", ")]
        kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), *[pa.int32()] * 4, pa.binary(), pa.list_(pa.int32()), pa.string()]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    return df.select(F.col(key).cast("long"), F.col(media)).mapInArrow(run, FRAME_SCHEMA)


def store_text(raw: bytes) -> bytes:
    """Bytes, filled with blanks to a positive multiple of 192, as frames of at most 256 rows of 192 samples."""
    size = max(WIDTH, -(-len(raw) // WIDTH) * WIDTH)
    samples = np.frombuffer(raw.ljust(size), np.uint8).reshape(-1, WIDTH)
    colours = cube()
    frames = [Frame(0, 0, samples[i : i + ROWS], colours, DELAY_CS, 1) for i in range(0, len(samples), ROWS)]
    return encode(frames, WIDTH, min(ROWS, len(samples)), colours)


def read_back(media: bytes) -> tuple[bytes, str, list[dict]]:
    """The stored bytes; a feature: frames, milliseconds, and the pixels in each of 64 colours as the frames show
    them; and the timed frames with their histograms."""
    width, height, _, stored = parse(media)
    frames, began, total = [], 0, np.zeros(64, np.int64)
    for f, rgb in shown(width, height, stored):
        own = histogram(rgb)
        total += own
        frames.append({"start_ms": began, "delay_ms": f.delay_cs * 10, "disposal": f.disposal, "transparent": f.transparent, "histogram": own.tolist()})
        began += f.delay_cs * 10
    feature = f"{len(frames)};{began};" + ",".join(map(str, total.tolist()))
    return b"".join(f.index.tobytes() for f in stored), feature, frames


def text_media(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Store each whole text as a GIF, read it back, and return digests of both forms (null text: empty)."""

    def run(batches):
        for batch in slices(batches, "text"):
            out = []
            for k, raw in zip(batch.column(0).to_pylist(), texts(batch.column(1)), strict=True):
                media = store_text(raw)
                got, feature, frames = read_back(media)
                out.append((k, len(raw), len(got), hashlib.sha256(got).hexdigest(), zlib.crc32(got[-16:]), len(media), hashlib.sha256(media).hexdigest(), feature, frames))
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), FRAMES]
            names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "frames"]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], names)

    return df.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, TEXT_SCHEMA)
