"""Media columns: Netpbm and BMP images to arrays, area-resized tiles, NPY bytes and difference hashes.

``decode`` reads P1 to P6 (bitmaps, grey and colour maps, 8 and 16 bit), P7 (arbitrary maps) and uncompressed 8/24/32-bit BMP; samples
of another maximum are scaled to the full range. ``area_resize`` averages
the covered source area of every target cell, from an integral image (two cumulative sums), so its cost does not
depend on the ratio. ``npy_bytes`` writes a tile as an NPY file. ``difference_hash`` compares neighbouring cells of a
9 x 8 resize.

Text payloads (``text_media``): the UTF-8 bytes, padded by zero bytes to a positive multiple of 64, are the samples of
a binary grey map of width 64. Null text counts as empty (64 zero bytes); repeated rows give repeated results; an empty
table gives an empty result; further columns of the input are ignored; a text of any length is one image.
"""

from __future__ import annotations

import hashlib
import io
import re
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from farpoint.session import ship

WIDTH = 64
_FIELD = re.compile(rb"(?:\s|#[^\n]*\n)*(\d+)")


def encode_pgm(samples: np.ndarray) -> bytes:
    h, w = samples.shape
    return b"P5\n%d %d\n255\n" % (w, h) + np.ascontiguousarray(samples, np.uint8).tobytes()


def encode_ppm(samples: np.ndarray) -> bytes:
    h, w, _ = samples.shape
    return b"P6\n%d %d\n255\n" % (w, h) + np.ascontiguousarray(samples, np.uint8).tobytes()


def encode_bmp(samples: np.ndarray) -> bytes:
    """24-bit, rows from the bottom, padded to 4 bytes."""
    h, w, _ = samples.shape
    row = (w * 3 + 3) // 4 * 4
    body = np.zeros((h, row), np.uint8)
    body[:, : w * 3] = samples[::-1, :, ::-1].reshape(h, w * 3)
    return struct.pack("<2sIHHI", b"BM", 54 + body.size, 0, 0, 54) + struct.pack("<IiiHHIIiiII", 40, w, h, 1, 24, 0, body.size, 2835, 2835, 0, 0) + body.tobytes()


def _scaled(flat: np.ndarray, top: int) -> np.ndarray:
    """Samples of 0 to top as the full range of 8 or 16 bit, rounded to nearest."""
    if not 0 < top < 65536:
        raise ValueError("the largest sample is from 1 to 65535")
    full = 255 if top < 256 else 65535
    if flat.size and (int(flat.max()) > top or int(flat.min()) < 0):
        raise ValueError("a sample is outside its range")
    if top != full:
        flat = (flat.astype(np.int64) * full + top // 2) // top
    return flat if flat.dtype == (np.uint8 if full == 255 else np.uint16) else flat.astype(np.uint8 if full == 255 else np.uint16)


def _header(data: bytes, count: int) -> tuple[list[int], int]:
    at, fields = 2, []
    for _ in range(count):
        m = _FIELD.match(data, at)
        if not m:
            raise ValueError("bad Netpbm header")
        fields.append(int(m[1]))
        at = m.end()
    return fields, at


def _body(data: bytes, kind, count: int, at: int) -> np.ndarray:
    if len(data) < at + count * np.dtype(kind).itemsize:
        raise ValueError("the samples end early")
    return np.frombuffer(data, kind, count, at)


def _decode_netpbm(data: bytes) -> np.ndarray:
    kind = data[:2]
    if kind == b"P7":
        return _decode_arbitrary(data)
    if kind in (b"P1", b"P4"):  # 1 is black
        (w, h), at = _header(data, 2)
        if kind == b"P1":
            bits = np.frombuffer(re.sub(rb"#[^\n]*|\s", b"", data[at:])[: w * h], np.uint8) - 48
            if len(bits) < w * h or bits.max(initial=0) > 1:
                raise ValueError("bad bitmap")
        else:
            row = (w + 7) // 8
            bits = np.unpackbits(_body(data, np.uint8, row * h, at + 1).reshape(h, row), axis=1)[:, :w]
        return ((1 - bits) * np.uint8(255)).reshape(h, w)
    (w, h, top), at = _header(data, 3)
    depth = 3 if kind in (b"P3", b"P6") else 1
    if kind in (b"P2", b"P3"):
        flat = np.array(re.sub(rb"#[^\n]*", b"", data[at:]).split(), np.int64)[: w * h * depth]
    else:
        flat = _body(data, np.uint8 if top < 256 else ">u2", w * h * depth, at + 1)
    return _scaled(flat, top).reshape((h, w) if depth == 1 else (h, w, 3))


def _decode_arbitrary(data: bytes) -> np.ndarray:
    """Named header lines; 1 to 4 channels, of which an alpha channel is dropped."""
    end = data.find(b"ENDHDR\n")
    if end < 0:
        raise ValueError("bad P7 header")
    fields = dict(line.split(None, 1) for line in data[3:end].splitlines() if line.strip() and not line.startswith(b"#") and b" " in line.strip())
    try:
        w, h, depth, top = (int(fields[k]) for k in (b"WIDTH", b"HEIGHT", b"DEPTH", b"MAXVAL"))
    except KeyError:
        raise ValueError("bad P7 header") from None
    if depth not in (1, 2, 3, 4):
        raise ValueError("1 to 4 channels are read")
    samples = _scaled(_body(data, np.uint8 if top < 256 else ">u2", w * h * depth, end + 7), top).reshape(h, w, depth)
    return samples[..., 0] if depth < 3 else samples[..., :3]


def _decode_bmp(data: bytes) -> np.ndarray:
    start = struct.unpack_from("<I", data, 10)[0]
    head, w, h, _, bits, packed = struct.unpack_from("<IiiHHI", data, 14)
    if packed not in (0, 3) or bits not in (8, 24, 32):
        raise ValueError("only uncompressed 8, 24 and 32-bit BMP are read")
    if w < 0:
        raise ValueError("negative width")
    row = (w * bits // 8 + 3) // 4 * 4
    rows = _body(data, np.uint8, row * abs(h), start).reshape(abs(h), row)[:, : w * bits // 8]
    if bits == 8:
        n = struct.unpack_from("<I", data, 46)[0] or 256
        palette = _body(data, np.uint8, n * 4, 14 + head).reshape(n, 4)
        if rows.max(initial=0) >= n:
            raise ValueError("a pixel is beyond the palette")
        out = palette[rows][..., 2::-1]
    else:
        out = rows.reshape(abs(h), w, bits // 8)[..., 2::-1]
    return out[::-1] if h > 0 else out


def decode(data: bytes) -> np.ndarray:
    if data[:2] == b"BM":
        return _decode_bmp(data)
    if data[:2] in (b"P1", b"P2", b"P3", b"P4", b"P5", b"P6", b"P7"):
        return _decode_netpbm(data)
    raise ValueError("neither Netpbm nor BMP")


def integral(samples: np.ndarray) -> np.ndarray:
    out = np.zeros((samples.shape[0] + 1, samples.shape[1] + 1), np.int64)
    np.cumsum(samples, axis=0, dtype=np.int64, out=out[1:, 1:])
    np.cumsum(out[1:, 1:], axis=1, out=out[1:, 1:])
    return out


def _edges(table: np.ndarray, n: int, axis: int) -> np.ndarray:
    """Integral values at n + 1 evenly spaced borders along an axis, interpolated between samples."""
    at = np.linspace(0, table.shape[axis] - 1, n + 1)
    low = np.minimum(at.astype(np.int64), table.shape[axis] - 2)
    part = (at - low).reshape((-1, 1) if axis == 0 else (1, -1))
    return np.take(table, low, axis) * (1 - part) + np.take(table, low + 1, axis) * part


def area_resize(samples: np.ndarray, height: int, width: int) -> np.ndarray:
    """Mean of the source area under every target cell; grey or per channel."""
    if samples.ndim == 3:
        return np.stack([area_resize(samples[..., c], height, width) for c in range(samples.shape[2])], -1)
    if samples.shape[0] * samples.shape[1] == 0:
        return np.zeros((height, width))
    corners = _edges(_edges(integral(samples), height, 0), width, 1)
    cells = corners[1:, 1:] - corners[:-1, 1:] - corners[1:, :-1] + corners[:-1, :-1]
    return cells / (samples.shape[0] / height * samples.shape[1] / width)


def grey(samples: np.ndarray) -> np.ndarray:
    """Integer luma, weights 77, 150, 29 of 256."""
    return samples if samples.ndim == 2 else (samples.astype(np.int64) @ np.array([77, 150, 29])) >> 8


def difference_hash(samples: np.ndarray) -> str:
    cells = area_resize(grey(samples), 8, 9)
    bits = (cells[:, 1:] > cells[:, :-1] + 1e-9).ravel()
    return "".join(f"{x:02x}" for x in np.packbits(bits))


def npy_bytes(tile: np.ndarray) -> bytes:
    out = io.BytesIO()
    np.save(out, tile, allow_pickle=False)
    return out.getvalue()


def tile(samples: np.ndarray, side: int = 16) -> bytes:
    return npy_bytes(np.rint(area_resize(samples, side, side)).clip(0, 255).astype(np.uint8))


def text_payload(text: str | None) -> tuple[int, bytes]:
    raw = (text or "").encode()
    return len(raw), raw + b"\0" * (max(WIDTH, -(-len(raw) // WIDTH) * WIDTH) - len(raw))


def image_columns(images: DataFrame, id_col: str, data_col: str, side: int = 16) -> DataFrame:
    """General form: (id, height, width, channels, tile as NPY bytes, dhash) of a column of image files; undecodable or null data gives nulls."""
    ship(images.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for data in b.column(1).to_pylist():
                try:
                    a = decode(data or b"")
                    if a.size == 0:
                        raise ValueError("no samples")
                    a = a if a.dtype == np.uint8 else ((a.astype(np.int64) * 255 + 32767) // 65535).astype(np.uint8)
                    rows.append((a.shape[0], a.shape[1], 1 if a.ndim == 2 else a.shape[2], tile(a, side), difference_hash(a)))
                except (ValueError, struct.error):
                    rows.append((None,) * 5)
            cols = list(zip(*rows)) or [()] * 5
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(c, t) for c, t in zip(cols, (pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.string())))], names=[id_col, "height", "width", "channels", "tile", "dhash"])

    kind = images.schema[id_col].dataType.simpleString()
    return images.select(id_col, data_col).mapInArrow(run, f"`{id_col}` {kind}, height int, width int, channels int, tile binary, dhash string")


def text_media(docs: DataFrame, keep: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Store every text as a grey map, read the stored bytes back and describe what was read, with the NPY tile. keep adds the file."""
    ship(docs.sparkSession)
    extra = [("tile", pa.binary()), *([("media", pa.binary())] if keep else [])]
    fields = [("n_bytes", pa.int64()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("feature", pa.string()), *extra]

    def one(text: str | None) -> tuple:
        n, payload = text_payload(text)
        stored = encode_pgm(np.frombuffer(payload, np.uint8).reshape(-1, WIDTH))
        samples = decode(stored)
        back = samples.tobytes()
        small = tile(samples)
        feature = difference_hash(samples) + ":" + hashlib.sha256(small).hexdigest()[:16]
        row = (n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(stored), hashlib.sha256(stored).hexdigest(), feature)
        return (*row, small, stored) if keep else (*row, small)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                cols = list(zip(*(one(t) for t in part.column(1).to_pylist())))
                yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(c, t) for c, (_, t) in zip(cols, fields))], names=[id_col, *(n for n, _ in fields)])

    kind = docs.schema[id_col].dataType.simpleString()
    sql = {pa.int64(): "long", pa.string(): "string", pa.binary(): "binary"}
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, " + ", ".join(f"{n} {sql[t]}" for n, t in fields))
