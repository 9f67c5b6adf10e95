"""Media columns: Netpbm and BMP decoded to numpy arrays, area-resized by integral images, NPY tiles and difference hashes.

Edge cases: a null text is the empty text; the empty text is one row of 64 zero samples; texts of any length are
one image of width 64; repeated rows give equal values; extra columns are ignored; an empty table gives no rows.
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

from graphpart.llm.common import ID, TEXT, arrow_map, strings

WIDTH = 64
_TOKEN = re.compile(rb"(?:\s|#[^\n]*\n)*([^\s#]+)")


def encode_pgm(pixels: np.ndarray) -> bytes:
    """8-bit grey samples as binary PGM (P5)."""
    h, w = pixels.shape
    return b"P5\n%d %d\n255\n" % (w, h) + np.ascontiguousarray(pixels, np.uint8).tobytes()


def encode_ppm(pixels: np.ndarray) -> bytes:
    """8-bit RGB samples as binary PPM."""
    h, w, _ = pixels.shape
    return b"P6\n%d %d\n255\n" % (w, h) + np.ascontiguousarray(pixels, np.uint8).tobytes()


def decode_netpbm(data: bytes) -> np.ndarray:
    """P1 to P6 as (h, w) or (h, w, 3); samples wider than 8 bits come as uint16; bitmaps as 0 (black) and 255."""
    magic, at = data[:2], 2
    if magic not in (b"P1", b"P2", b"P3", b"P4", b"P5", b"P6"):
        raise ValueError("not a Netpbm image")
    head: list[int] = []
    while len(head) < (2 if magic in (b"P1", b"P4") else 3):
        m = _TOKEN.match(data, at)
        if m is None:
            raise ValueError("truncated Netpbm header")
        head.append(int(m[1]))
        at = m.end()
    w, h = head[:2]
    most = head[2] if len(head) == 3 else 1
    depth = 3 if magic in (b"P3", b"P6") else 1
    kind = np.dtype(np.uint8) if most < 256 else np.dtype(">u2")
    if magic in (b"P5", b"P6"):
        flat = np.frombuffer(data, kind, h * w * depth, at + 1).astype(kind.newbyteorder("="))
    elif magic == b"P4":
        row = (w + 7) // 8
        bits = np.unpackbits(np.frombuffer(data, np.uint8, h * row, at + 1).reshape(h, row), axis=1)[:, :w]
        flat = np.where(bits == 1, 0, 255).astype(np.uint8).ravel()
    else:
        body = re.sub(rb"#[^\n]*", b"", data[at:])
        if magic == b"P1":
            flat = np.array([0 if c == 49 else 255 for c in body if c in (48, 49)], np.uint8)
        else:
            flat = np.array(body.split(), kind.newbyteorder("="))
    if flat.size < h * w * depth:
        raise ValueError("truncated Netpbm samples")
    flat = flat[: h * w * depth]
    return flat.reshape(h, w) if depth == 1 else flat.reshape(h, w, 3)


def encode_bmp(pixels: np.ndarray) -> bytes:
    """8-bit grey samples as an uncompressed, palette BMP, bottom row first."""
    h, w = pixels.shape
    stride = (w + 3) // 4 * 4
    rows = np.zeros((h, stride), np.uint8)
    rows[:, :w] = pixels[::-1]
    palette = np.repeat(np.arange(256, dtype=np.uint8)[:, None], 4, axis=1)
    palette[:, 3] = 0
    offset = 14 + 40 + 1024
    head = struct.pack("<2sIHHI", b"BM", offset + rows.size, 0, 0, offset)
    return head + struct.pack("<IiiHHIIiiII", 40, w, h, 1, 8, 0, rows.size, 2835, 2835, 256, 0) + palette.tobytes() + rows.tobytes()


def decode_bmp(data: bytes) -> np.ndarray:
    """Uncompressed BMP of 1, 4, 8, 24 or 32 bits; grey palettes give (h, w), others (h, w, 3) RGB."""
    if data[:2] != b"BM":
        raise ValueError("not a BMP image")
    (offset,) = struct.unpack_from("<I", data, 10)
    size, w, h, _, bits, packed = struct.unpack_from("<IiiHHI", data, 14)
    (used,) = struct.unpack_from("<I", data, 46)
    if packed not in (0, 3) or bits not in (1, 4, 8, 24, 32):
        raise ValueError("BMP compression or depth not supported")
    stride = (w * bits + 31) // 32 * 4
    rows = np.frombuffer(data, np.uint8, abs(h) * stride, offset).reshape(abs(h), stride)
    rows = rows[::-1] if h > 0 else rows
    if bits >= 24:
        return np.ascontiguousarray(rows[:, : w * bits // 8].reshape(abs(h), w, bits // 8)[:, :, 2::-1])
    if bits == 8:
        index = rows[:, :w]
    elif bits == 4:
        index = np.stack([rows >> 4, rows & 15], axis=2).reshape(abs(h), -1)[:, :w]
    else:
        index = np.unpackbits(rows, axis=1)[:, :w]
    n = used or 1 << bits
    palette = np.frombuffer(data, np.uint8, n * 4, 14 + size).reshape(n, 4)[:, 2::-1]
    if (palette[:, 0] == palette[:, 1]).all() and (palette[:, 1] == palette[:, 2]).all():
        return np.ascontiguousarray(palette[:, 0][index])
    return palette[index]


def decode(data: bytes) -> np.ndarray:
    return decode_bmp(data) if data[:2] == b"BM" else decode_netpbm(data)


def grey(pixels: np.ndarray) -> np.ndarray:
    """Luma of RGB samples (integer weights), grey samples as they are."""
    if pixels.ndim == 2:
        return pixels
    r, g, b = (pixels[:, :, i].astype(np.int64) for i in range(3))
    return (299 * r + 587 * g + 114 * b) // 1000


def resize_area(pixels: np.ndarray, h: int, w: int) -> np.ndarray:
    """Exact mean over each target cell, read off the summed-area table (linear between its entries)."""
    img = grey(pixels)
    table = np.zeros((img.shape[0] + 1, img.shape[1] + 1), np.int64)
    np.cumsum(np.cumsum(img, axis=0, dtype=np.int64), axis=1, out=table[1:, 1:])

    def cut(n: int, m: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        at = np.arange(m + 1) * n  # in units of 1/m
        low = np.minimum(at // m, n - 1)
        return low, low + 1, (at - low * m) / m

    y0, y1, fy = cut(img.shape[0], h)
    x0, x1, fx = cut(img.shape[1], w)
    rows = table[y0] * (1 - fy)[:, None] + table[y1] * fy[:, None]
    grid = rows[:, x0] * (1 - fx) + rows[:, x1] * fx
    cells = grid[1:, 1:] - grid[:-1, 1:] - grid[1:, :-1] + grid[:-1, :-1]
    return cells * (h * w / (img.shape[0] * img.shape[1]))


def difference_hash(pixels: np.ndarray) -> int:
    """64 bits: whether each cell of an 8 x 9 reduction is darker than its right neighbour."""
    small = np.round(resize_area(pixels, 8, 9), 6)
    return int.from_bytes(np.packbits(small[:, :-1] < small[:, 1:]).tobytes(), "big")


def npy_tile(pixels: np.ndarray, side: int = 16) -> bytes:
    """The reduction to side x side 8-bit samples, as the bytes of an .npy file."""
    out = io.BytesIO()
    np.lib.format.write_array(out, np.floor(resize_area(pixels, side, side) + 0.5).astype(np.uint8), allow_pickle=False)
    return out.getvalue()


def payload_of(text: str) -> tuple[bytes, int]:
    """UTF-8 of the text, zero bytes up to a positive multiple of WIDTH; and the length before them."""
    raw = text.encode()
    return raw + bytes(max(WIDTH, -(-len(raw) // WIDTH) * WIDTH) - len(raw)), len(raw)


_FIELDS = [
    ("n_bytes", pa.int64()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()),
    ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("feature", pa.string()), ("tile_crc32", pa.int64()), ("tile_npy", pa.binary()),
]
_SCHEMA = "n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, tile_crc32 long, tile_npy binary"


def _digest(text: str, fmt: str) -> tuple:
    payload, n = payload_of(text)
    pixels = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH)
    stored = encode_bmp(pixels) if fmt == "bmp" else encode_pgm(pixels)
    image = decode(stored)
    back = image.tobytes()
    tile = npy_tile(image)
    return n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(stored), hashlib.sha256(stored).hexdigest(), f"{difference_hash(image):016x}", zlib.crc32(tile), tile


def media_features(docs: DataFrame, fmt: str = "pgm") -> DataFrame:
    """(doc_id, digests, feature, tile_crc32, tile_npy) of each text stored as an image and read back; a map, no shuffle."""
    if fmt not in ("pgm", "bmp"):
        raise ValueError("fmt is pgm or bmp")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in (batch.slice(i, 512) for i in range(0, batch.num_rows, 512)):
                cols = list(zip(*(_digest(x, fmt) for x in strings(part, TEXT)), strict=True))
                yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(c, t) for c, (_, t) in zip(cols, _FIELDS, strict=True))], names=[ID, *(n for n, _ in _FIELDS)])

    return arrow_map(docs.select(ID, TEXT), run, f"{ID} {docs.schema[ID].dataType.simpleString()}, {_SCHEMA}")


def write_tiles(features: DataFrame, path: str) -> None:
    """NPY tiles with their hashes, one row each, as Parquet."""
    features.select(ID, "feature", "tile_npy").write.mode("overwrite").parquet(path)
