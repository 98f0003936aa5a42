"""Media columns: Netpbm and BMP to numpy arrays, area resize by integral images, NPY tiles, difference hashes.

`decode` reads P1 to P6 (plain and raw, 8 and 16 bit) and uncompressed BMP (1, 4, 8, 24, 32 bit, either row order);
`encode_pgm` gives bytes losslessly as 8-bit grey samples, which are stored as NPY tiles.  Damaged or truncated files
give None in columns.

Edge cases: null and empty texts are 64 zero bytes; equal texts give equal values whatever the batch; any length works,
one image at a time: images are summed and cut in stripes of rows, so a long text needs a few times its own bytes.  An
empty table gives an empty result.
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
from pyspark.sql import DataFrame, SparkSession

from .common import table

WIDTH = 64
_TOKEN = re.compile(rb"(?:\s|#[^\n]*\n)*([0-9]+)")


def encode_pgm(payload: bytes, width: int = WIDTH) -> bytes:
    """Raw grey map with one sample a byte; len(payload) must be a multiple of the width."""
    if not payload or len(payload) % width:
        raise ValueError("payload must fill whole rows")
    return b"P5\n%d %d\n255\n" % (width, len(payload) // width) + payload


def decode_netpbm(data: bytes) -> np.ndarray:
    """P1..P6 -> (height, width) or (height, width, 3), uint8 or uint16.  Bitmaps: 0 is black, 255 white."""
    kind = data[:2]
    if kind not in (b"P1", b"P2", b"P3", b"P4", b"P5", b"P6"):
        raise ValueError("not a Netpbm file")
    at, head = 2, []
    for _ in range(2 if kind in (b"P1", b"P4") else 3):
        m = _TOKEN.match(data, at)
        if not m:
            raise ValueError("header is cut off")
        head.append(int(m[1]))
        at = m.end()
    w, h = head[:2]
    top = head[2] if len(head) > 2 else 1
    if w < 1 or h < 1 or not 0 < top < 65536:
        raise ValueError("bad size or depth")
    colours = 3 if kind in (b"P3", b"P6") else 1
    if kind in (b"P1", b"P2", b"P3"):
        body = re.sub(rb"#[^\n]*", b" ", data[at:])
        values = [c - 48 for c in body if c in b"01"] if kind == b"P1" else [int(x) for x in body.split()]
        if len(values) < w * h * colours:
            raise ValueError("samples are missing")
        a = np.array(values[: w * h * colours], np.uint16 if top > 255 else np.uint8)
    elif kind == b"P4":
        a = np.unpackbits(np.frombuffer(data, np.uint8, h * ((w + 7) // 8), at + 1).reshape(h, -1), axis=1)[:, :w].ravel()
    else:
        a = np.frombuffer(data, np.uint8 if top < 256 else ">u2", w * h * colours, at + 1)
        a = a if top < 256 else a.astype(np.uint16)
    if kind in (b"P1", b"P4"):
        a = ((1 - a) * 255).astype(np.uint8)
    return a.reshape((h, w, 3) if colours == 3 else (h, w))


def decode_bmp(data: bytes) -> np.ndarray:
    """Uncompressed BMP -> (height, width, 3) uint8, red first, top row first."""
    if data[:2] != b"BM" or len(data) < 54:
        raise ValueError("not a BMP file")
    offset, header, w, h, _, bits, packed = struct.unpack_from("<I I i i H H I", data, 10)
    if packed not in (0, 3) or bits not in (1, 4, 8, 24, 32) or w < 1 or h == 0 or (packed == 3 and bits != 32):
        raise ValueError("compressed or of unknown depth")
    stride = (w * bits + 31) // 32 * 4
    rows = np.frombuffer(data, np.uint8, stride * abs(h), offset).reshape(abs(h), stride)
    if bits >= 24:
        a = rows[:, : w * bits // 8].reshape(abs(h), w, bits // 8)[:, :, 2::-1]
    else:
        used = struct.unpack_from("<I", data, 46)[0] or 1 << bits
        palette = np.zeros((256, 3), np.uint8)
        palette[:used] = np.frombuffer(data, np.uint8, used * 4, 14 + header).reshape(-1, 4)[:, 2::-1]
        index = rows if bits == 8 else np.unpackbits(rows, axis=1) if bits == 1 else np.stack([rows >> 4, rows & 15], 2).reshape(abs(h), -1)
        a = palette[index[:, :w]]
    return np.ascontiguousarray(a if h < 0 else a[::-1])


def decode(data: bytes) -> np.ndarray:
    return decode_bmp(data) if data[:2] == b"BM" else decode_netpbm(data)


def grey(a: np.ndarray) -> np.ndarray:
    """Luminance (weights .299, .587, .114) of colours as float64; grey samples as they are."""
    return a if a.ndim == 2 else a[:, :, :3] @ np.array([0.299, 0.587, 0.114])


def _stripe_sums(a: np.ndarray, cells: int, stripe: int = 4096) -> np.ndarray:
    """Sums of the rows under each of so many even cells: the integral along the rows, made stripe by stripe and kept only
    where a cell begins, between two rows in proportion."""
    n = len(a)
    x = np.arange(cells + 1) * n / cells
    i = np.minimum(x.astype(np.int64), n - 1)
    below, above = (np.zeros((cells + 1, *a.shape[1:])) for _ in range(2))
    total = np.zeros(a.shape[1:])
    for lo in range(0, n, stripe):
        part = np.cumsum(a[lo : lo + stripe].astype(np.float64), 0) + total
        for place, out in ((i, below), (i + 1, above)):
            here = (place > lo) & (place <= lo + len(part))
            out[here] = part[place[here] - lo - 1]
        total = part[-1]
    f = (x - i).reshape(-1, *[1] * (a.ndim - 1))
    return np.diff(below * (1 - f) + above * f, axis=0)


def area_resize(a: np.ndarray, height: int, width: int) -> np.ndarray:
    """Mean of the exact source area under each target cell: the integral image, read at fractional corners."""
    h, w = a.shape[:2]
    both = _stripe_sums(np.moveaxis(_stripe_sums(a, height), 1, 0), width)
    return np.moveaxis(both, 0, 1) * (height * width) / (h * w)


def difference_hash(a: np.ndarray, size: int = 8) -> int:
    """size * size bits: is each cell of the resized image darker than its right neighbour?"""
    small = np.round(area_resize(grey(a), size, size + 1), 6)
    return int("".join("1" if x else "0" for x in (small[:, :-1] < small[:, 1:]).ravel()), 2)


def npy_tiles(a: np.ndarray, tile: int = 256) -> Iterator[tuple[int, int, bytes]]:
    """(row, column, NPY bytes) of each tile; tiles at the edge are smaller."""
    for y in range(0, a.shape[0], tile):
        for x in range(0, a.shape[1], tile):
            out = io.BytesIO()
            np.save(out, np.ascontiguousarray(a[y : y + tile, x : x + tile]), allow_pickle=False)
            yield y // tile, x // tile, out.getvalue()


def media_tiles(images: DataFrame, column: str = "data", key: str = "id", height: int = 64, width: int = 64, tile: int = 32) -> DataFrame:
    """key, ok, height, width, dhash (hex), tile_row, tile_col, npy: images resized and cut into NPY tiles; one row with
    nulls and ok false for a null or damaged image."""
    kind = images.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for k, raw in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                try:
                    a = decode(raw or b"")
                    code = f"{difference_hash(a):016x}"
                    small = np.clip(np.rint(area_resize(a, height, width)), 0, np.iinfo(a.dtype).max).astype(a.dtype)
                    out += [(k, True, *a.shape[:2], code, y, x, t) for y, x, t in npy_tiles(small, tile)]
                except (ValueError, struct.error, IndexError):
                    out.append((k, False, None, None, None, None, None, None))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out) if out else [[]] * 8, [b.schema[0].type, pa.bool_(), pa.int32(), pa.int32(), pa.string(), pa.int32(), pa.int32(), pa.binary()])], names=[key, "ok", "height", "width", "dhash", "tile_row", "tile_col", "npy"])

    return images.select(key, column).mapInArrow(run, f"{key} {kind}, ok boolean, height int, width int, dhash string, tile_row int, tile_col int, npy binary")


def payload_of(text: bytes) -> bytes:
    return text + bytes(-len(text) % WIDTH if text else WIDTH)


def text_media(docs: DataFrame, tile: int = 1024) -> DataFrame:
    """doc_id, text -> each text's bytes as a grey map, decoded, stored as NPY tiles of up to `tile` rows, read back from
    the tiles and digested.  media_*: of the tiles in order; feature: size and difference hash of the image read back."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for i, text in zip(b.column(0).to_pylist(), b.column(1)):
                raw = (text.as_py() or "").encode()
                stored, size, parts = hashlib.sha256(), 0, []
                for _, _, npy in npy_tiles(decode(encode_pgm(payload_of(raw))), tile):
                    stored.update(npy)
                    size += len(npy)
                    parts.append(np.load(io.BytesIO(npy), allow_pickle=False))
                image = np.concatenate(parts) if len(parts) > 1 else parts[0]
                feature = f"{image.shape[0]}x{image.shape[1]}:{difference_hash(image):016x}"
                out.append((i, len(raw), image.size, hashlib.sha256(image).hexdigest(), zlib.crc32(image[-1]), size, stored.hexdigest(), feature))
            kinds = [b.schema[0].type, pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out) if out else [[]] * 8, kinds)], names=NAMES)

    return docs.select("doc_id", "text").mapInArrow(run, SCHEMA)


SCHEMA = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
NAMES = [x.split()[0] for x in SCHEMA.split(", ")]


def op6_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text_media(table(spark, sf_dir, "documents"))
