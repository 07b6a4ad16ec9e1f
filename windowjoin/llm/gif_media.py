"""GIF media columns: samples to GIF bytes, GIF bytes to timed frames and features.

``write_gif`` stores 8-bit samples as a GIF89a animation: a grey palette of 256 colours,
frames of ``WIDTH`` columns with at most ``ROWS`` rows, real LZW code streams with growing
code widths. ``read_gif`` decodes any GIF of this family: global and local palettes,
interlacing, sub-blocks, early and late clear codes, transparency and the disposal
methods, and gives each frame's delay, its palette indices and the canvas after it.

``media_table`` stores the media column as Parquet in the shared folder, ``features``
reads it back, decodes it and computes a colour histogram of ``BINS`` bins over all
frames, its mean and its spread.

Defined cases: a null or empty text becomes one padded frame; equal texts give equal
media; repeated rows are stored again; an empty table gives an empty table; extra
columns are not read; a text of any length becomes as many frames as it needs.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from windowjoin.llm import common

WIDTH, ROWS, BINS, DELAY = 576, 64, 16, 4
PAD = 255


# -- LZW -------------------------------------------------------------------------------


def widths(n: int, size: int) -> np.ndarray:
    """Bits of the codes that follow a clear code, by their place; size: the minimum code size.

    Every code but the first after a clear adds an entry to the decoder's table, and a
    code has as many bits as the table's size then needs.
    """
    table = (1 << size) + 2 + np.maximum(np.arange(n) - 1, 0)
    return np.clip(np.floor(np.log2(table)).astype(np.int64) + 1, size + 1, 12)


_WIDTHS: dict[int, np.ndarray] = {}


def lzw_codes(data: bytes, size: int = 8) -> tuple[list[int], list[int]]:
    """Codes of one frame, and the places of the clear codes among them."""
    clear, stop = 1 << size, (1 << size) + 1
    out, clears = [clear], [0]
    if data:
        known: dict[int, int] = {}
        rest = iter(data)
        add, free, prefix = out.append, clear + 2, next(rest)
        for b in rest:
            key = prefix << 8 | b
            if key in known:
                prefix = known[key]
                continue
            add(prefix)
            prefix = b
            known[key] = free
            free += 1
            if free == 4096:  # the table is full: begin anew
                clears.append(len(out))
                add(clear)
                known.clear()
                free = clear + 2
        add(prefix)
    out.append(stop)
    return out, clears


def lzw_bytes(data: bytes, size: int = 8) -> bytes:
    """The code stream of one frame, packed from the low bits up."""
    codes, clears = lzw_codes(data, size)
    if size not in _WIDTHS:
        _WIDTHS[size] = widths(4200, size)
    table = _WIDTHS[size]
    ends = [*clears[1:], len(codes)]
    bits = np.empty(len(codes), np.int64)
    bits[0] = size + 1
    for a, b in zip(clears, ends, strict=True):  # the codes after a clear, and the next clear itself
        n = min(b + 1, len(codes)) - a - 1
        bits[a + 1 : a + 1 + n] = table[:n]
    value = np.array(codes, np.uint64)
    at = np.cumsum(bits) - bits
    total = int(bits.sum())
    out = np.zeros(total // 8 + 5, np.uint8)
    shifted = value << (at & 7).astype(np.uint64)
    byte = at >> 3
    for k in range(3):  # a code of up to 12 bits touches three bytes; no two codes share a bit
        out[:] |= np.bincount(byte + k, (shifted >> np.uint64(8 * k) & np.uint64(255)).astype(np.float64), len(out)).astype(np.uint8)
    return out[: (total + 7) // 8].tobytes()


def lzw_decode(stream: bytes, size: int) -> bytes:
    """The indices of a code stream; codes of one width are unpacked together."""
    clear, stop = 1 << size, (1 << size) + 1
    raw = np.frombuffer(stream + b"\0\0\0", np.uint8).astype(np.uint32)
    limit = 8 * len(stream)
    roots = [bytes([i]) for i in range(clear)] + [b"", b""]
    out: list[bytes] = []
    table, prev, width, at = list(roots), b"", size + 1, 0
    while at + width <= limit:
        # codes until the width grows, the table is full or the data end
        free = len(table)
        n = (limit - at) // width
        if free < 4096:
            n = min(n, (1 << width) - free + (0 if prev else 1))
        pos = at + width * np.arange(n)
        byte = pos >> 3
        word = raw[byte] | raw[byte + 1] << 8 | raw[byte + 2] << 16
        codes = word >> (pos & 7).astype(np.uint32) & ((1 << width) - 1)
        control = np.flatnonzero((codes == clear) | (codes == stop))
        run = codes[: control[0]].tolist() if len(control) else codes.tolist()
        add, grow = out.append, table.append
        if run and not prev:
            prev = table[run.pop(0)]
            add(prev)
        if free < 4096:
            for code in run:
                if code < free:
                    entry = table[code]
                    grow(prev + entry[:1])
                elif code == free:
                    entry = prev + prev[:1]
                    grow(entry)
                else:
                    raise ValueError("a code beyond the table")
                free += 1
                add(entry)
                prev = entry
        else:
            for code in run:
                prev = table[code]
                add(prev)
        if not len(control):
            at += width * n
            width = min(12, max(width, free.bit_length()))
            continue
        if codes[control[0]] == stop:
            break
        at += width * (int(control[0]) + 1)
        table, prev, width = list(roots), b"", size + 1
    return b"".join(out)


# -- containers ------------------------------------------------------------------------


@dataclass
class Frame:
    left: int
    top: int
    width: int
    height: int
    delay: int
    disposal: int
    transparent: int | None
    indices: np.ndarray
    palette: np.ndarray
    canvas: np.ndarray | None = field(default=None)


def blocks(data: bytes) -> bytes:
    return b"".join(bytes([len(data[i : i + 255])]) + data[i : i + 255] for i in range(0, len(data), 255)) + b"\0"


GREY = np.repeat(np.arange(256, dtype=np.uint8), 3).tobytes()


def write_gif(samples: bytes, width: int = WIDTH, rows: int = ROWS, delay: int = DELAY) -> bytes:
    """An animation whose frames hold the samples row by row; len(samples) is a multiple of width."""
    if not samples or len(samples) % width:
        raise ValueError("samples must fill whole rows")
    height = min(rows, len(samples) // width)
    out = [b"GIF89a", struct.pack("<HHBBB", width, height, 0xF7, 0, 0), GREY]
    for at in range(0, len(samples), width * rows):
        part = samples[at : at + width * rows]
        out.append(b"\x21\xf9\x04" + struct.pack("<BHBB", 1 << 2, delay, 0, 0))
        out.append(b"\x2c" + struct.pack("<HHHHB", 0, 0, width, len(part) // width, 0) + b"\x08")
        out.append(blocks(lzw_bytes(part)))
    return b"".join([*out, b"\x3b"])


def _sub_blocks(data: bytes, at: int) -> tuple[bytes, int]:
    parts = []
    while data[at]:
        parts.append(data[at + 1 : at + 1 + data[at]])
        at += 1 + data[at]
    return b"".join(parts), at + 1


def interlaced_rows(height: int) -> np.ndarray:
    """The rows in the order in which an interlaced frame stores them."""
    return np.concatenate([np.arange(a, height, b) for a, b in ((0, 8), (4, 8), (2, 4), (1, 2))])


def read_gif(data: bytes) -> list[Frame]:
    """The timed frames of a GIF; ``canvas`` is the RGBA picture that is shown with each frame."""
    out = []
    for frame in frames_of(data):
        frame.canvas = frame.canvas.copy()
        out.append(frame)
    return out


def frames_of(data: bytes) -> Iterator[Frame]:
    """The same one by one: a frame's canvas is as shown until the next frame is asked for."""
    if data[:6] not in (b"GIF87a", b"GIF89a"):
        raise ValueError("no GIF")
    width, height, flags, _, _ = struct.unpack_from("<HHBBB", data, 6)
    at, palette = 13, np.zeros((0, 3), np.uint8)
    if flags & 0x80:
        n = 2 << (flags & 7)
        palette = np.frombuffer(data, np.uint8, 3 * n, at).reshape(n, 3)
        at += 3 * n
    canvas = np.zeros((height, width, 4), np.uint8)
    delay, disposal, clear = 0, 0, None
    while data[at] != 0x3B:
        kind = data[at]
        if kind == 0x21:
            label = data[at + 1]
            body, at = _sub_blocks(data, at + 2)
            if label == 0xF9:
                bits, delay, index = struct.unpack_from("<BHB", body)
                disposal, clear = bits >> 2 & 7, index if bits & 1 else None
            continue
        if kind != 0x2C:
            raise ValueError("unknown block")
        left, top, w, h, bits = struct.unpack_from("<HHHHB", data, at + 1)
        at += 10
        own = palette
        if bits & 0x80:
            n = 2 << (bits & 7)
            own = np.frombuffer(data, np.uint8, 3 * n, at).reshape(n, 3)
            at += 3 * n
        size = data[at]
        stream, at = _sub_blocks(data, at + 1)
        pixels = np.frombuffer(lzw_decode(stream, size), np.uint8)
        if len(pixels) < w * h:
            raise ValueError("a frame ends early")
        pixels = pixels[: w * h].reshape(h, w)
        if bits & 0x40:
            rows = np.empty_like(pixels)
            rows[interlaced_rows(h)] = pixels
            pixels = rows
        before = canvas.copy() if disposal == 3 else None
        place = canvas[top : top + h, left : left + w]
        seen = pixels[: place.shape[0], : place.shape[1]]
        if clear is None:
            place[..., :3] = own[seen]
            place[..., 3] = 255
        else:  # what was there stays visible
            shown = seen != clear
            place[shown, :3] = own[seen[shown]]
            place[shown, 3] = 255
        yield Frame(left, top, w, h, delay, disposal, clear, pixels, own, canvas)
        if disposal == 2:
            place[:] = 0
        elif disposal == 3:
            canvas = before
        delay, disposal, clear = 0, 0, None


# -- columns ---------------------------------------------------------------------------


def payload(text: bytes, unit: int = WIDTH) -> bytes:
    """The bytes, padded with 255 to a positive multiple of the unit."""
    return text + bytes([PAD]) * (max(unit, -(-len(text) // unit) * unit) - len(text))


def histogram(canvas: np.ndarray, bins: int = BINS) -> np.ndarray:
    """Shares of the shown colours (their luminance) per bin; a pixel that shows nothing does not count."""
    r, g, b, alpha = (canvas[..., k] for k in range(4))
    grey = (r * np.uint32(299) + g * np.uint32(587) + b * np.uint32(114)) // np.uint32(1000 * 256 // bins)
    counts = np.bincount(grey[alpha > 0] if not alpha.all() else grey.ravel(), minlength=bins)
    return counts / max(1, counts.sum())


def media_table(docs: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, media): the stored media column, read back from the shared folder."""
    common.ship(docs.sparkSession)

    def rows(batches):
        for batch in batches:
            for part in common.cut(batch, most=4 << 20):
                data, ends = common.utf8(part.column("text"))
                at, raw = ends.tolist(), data.tobytes()
                media = [write_gif(payload(raw[a:b])) for a, b in zip(at[:-1], at[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(np.diff(ends), pa.int64()), pa.array(media, pa.binary())], names=["doc_id", "n_bytes", "media"])

    media = common.texts(docs, "doc_id").mapInArrow(rows, "doc_id long, n_bytes long, media binary")
    return common.written(media, "media", compression="zstd", **{"parquet.enable.dictionary": "false", "parquet.block.size": str(32 << 20)})


FEATURES = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_frames int, duration_cs int, frames array<struct<delay_cs:int,disposal:int,histogram:array<double>>>"
TIMED = pa.list_(pa.struct([("delay_cs", pa.int32()), ("disposal", pa.int32()), ("histogram", pa.list_(pa.float64()))]))


def described(stored: bytes) -> tuple:
    """The columns of one stored medium: digests of its samples, the colours of what it shows (each
    frame by its time, by number where none has any), and its timed frames."""
    samples, timed = [], []
    for f in frames_of(stored):
        samples.append(f.indices.tobytes())
        timed.append({"delay_cs": f.delay, "disposal": f.disposal, "histogram": histogram(f.canvas)})
    data = b"".join(samples)
    times = np.array([t["delay_cs"] for t in timed], np.float64)
    shares = np.average([t["histogram"] for t in timed], axis=0, weights=times if times.any() else None)
    mean = float(shares @ np.arange(BINS))
    spread = float(np.sqrt(max(0.0, shares @ (np.arange(BINS) - mean) ** 2)))
    text = ",".join(f"{x:.6f}" for x in (*shares, mean, spread))
    return len(data), hashlib.sha256(data).hexdigest(), zlib.crc32(data[-32:]), len(stored), hashlib.sha256(stored).hexdigest(), text, len(timed), int(times.sum()), timed


def features(media: DataFrame) -> DataFrame:
    """Decode the stored media: digests of the samples, the colour-histogram columns, the timed frames."""
    common.ship(media.sparkSession)

    def rows(batches):
        names = [c.split()[0] for c in FEATURES.split(", ")]
        kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int32(), pa.int32(), TIMED]
        for batch in batches:
            for part in common.cut(batch, "media", most=2 << 20):
                cols = zip(*map(described, part.column("media").to_pylist()), strict=True)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("n_bytes"), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], names=names)

    return media.select("doc_id", "n_bytes", "media").mapInArrow(rows, FEATURES)
