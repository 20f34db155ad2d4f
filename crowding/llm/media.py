"""Media columns: Netpbm and BMP to numpy, box resize by integral images, NPY tiles, difference hashes.

Edge cases: null or undecodable bytes give null arrays, tiles and hashes (decode() itself raises ValueError);
images of one pixel or with sides below the hash grid resize by repeated pixels; equal bytes give equal
tiles and hashes; an empty table stays empty; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from crowding.llm.common import open_fs, slices, table, utf8

_SPACE_OR_COMMENT = re.compile(rb"(?:[ \t\r\n\v\f]|#[^\n]*(?:\n|$))+")
#: Rows of a tile written by the text query; tiles are as wide as its images.
TILE = 256
#: Bytes a row of the image that carries a text.
WIDTH = 64


def _header(data: bytes, fields: int) -> tuple[list[int], int]:
    at, out = 2, []
    while len(out) < fields:
        if m := _SPACE_OR_COMMENT.match(data, at):
            at = m.end()
        m = re.compile(rb"\d+").match(data, at)
        if not m:
            raise ValueError("bad Netpbm header")
        out.append(int(m[0]))
        at = m.end()
    return out, at


def decode_netpbm(data: bytes) -> np.ndarray:
    """P1 to P6 as (height, width) or (height, width, 3); bitmaps as 0 for white and 1 for black."""
    kind = data[1] - 48
    if data[:1] != b"P" or not 1 <= kind <= 6:
        raise ValueError("not Netpbm")
    dims, at = _header(data, 2 if kind in (1, 4) else 3)
    w, h = dims[:2]
    shape = (h, w, 3) if kind in (3, 6) else (h, w)
    n = int(np.prod(shape))
    if kind == 1:
        flat = np.frombuffer(re.sub(rb"[^01]", b"", re.sub(rb"#[^\n]*", b"", data[at:])), np.uint8)[:n] - 48
    elif kind in (2, 3):
        flat = np.array(re.sub(rb"#[^\n]*", b"", data[at:]).split()[:n], dtype=np.uint16 if dims[2] > 255 else np.uint8)
    elif kind == 4:
        row = (w + 7) // 8
        bits = np.frombuffer(data, np.uint8, row * h, at + 1).reshape(h, row)
        flat = np.unpackbits(bits, axis=1)[:, :w].ravel()
    else:
        wide = dims[2] > 255
        flat = np.frombuffer(data, ">u2" if wide else np.uint8, n, at + 1)
        flat = flat.astype(np.uint16) if wide else flat
    if flat.size != n:
        raise ValueError("short Netpbm data")
    return flat.reshape(shape)


def encode_pgm(image: np.ndarray) -> bytes:
    """8-bit grey samples as a binary PGM."""
    return b"P5\n%d %d\n255\n" % (image.shape[1], image.shape[0]) + np.ascontiguousarray(image, np.uint8).tobytes()


def decode_bmp(data: bytes) -> np.ndarray:
    """Uncompressed BMP of 8 (palette), 24 or 32 bits as (height, width, 3) RGB."""
    if data[:2] != b"BM" or len(data) < 54:
        raise ValueError("not BMP")
    start, header, w, h, _, bits, packed = struct.unpack_from("<I I i i H H I", data, 10)
    if packed not in (0, 3) or bits not in (8, 24, 32) or w <= 0 or h == 0:
        raise ValueError("BMP of a kind that is not read")
    stride, rows = (w * bits // 8 + 3) // 4 * 4, abs(h)
    raw = np.frombuffer(data, np.uint8, stride * rows, start).reshape(rows, stride)
    raw = raw[::-1] if h > 0 else raw
    if bits == 8:
        colors = struct.unpack_from("<I", data, 46)[0] or 256
        palette = np.frombuffer(data, np.uint8, 4 * colors, 14 + header).reshape(colors, 4)
        return palette[raw[:, :w], 2::-1]
    step = bits // 8
    return raw[:, : w * step].reshape(rows, w, step)[:, :, 2::-1]


def decode(data: bytes) -> np.ndarray:
    return decode_bmp(data) if data[:2] == b"BM" else decode_netpbm(data)


def grey(image: np.ndarray) -> np.ndarray:
    return image if image.ndim == 2 else image.astype(np.float64) @ np.array([0.299, 0.587, 0.114])


def resize(image: np.ndarray, height: int, width: int) -> np.ndarray:
    """Mean of each output cell's area, from an integral image read at fractional corners."""
    h, w = image.shape
    total = np.zeros((h + 1, w + 1))
    np.cumsum(np.cumsum(image, axis=0, dtype=np.float64), axis=1, out=total[1:, 1:])

    def along(a: np.ndarray, n: int, axis: int) -> np.ndarray:
        at = np.linspace(0, a.shape[axis] - 1, n + 1)
        low = np.minimum(at.astype(int), a.shape[axis] - 2)
        part = (at - low).reshape((-1, 1) if axis == 0 else (1, -1))
        return np.take(a, low, axis) * (1 - part) + np.take(a, low + 1, axis) * part

    corners = along(along(total, height, 0), width, 1)
    sums = corners[1:, 1:] - corners[:-1, 1:] - corners[1:, :-1] + corners[:-1, :-1]
    return sums * (height * width / (h * w))


def difference_hash(image: np.ndarray, side: int = 8) -> str:
    """side*side bits, as hex: whether a cell of the resized image is brighter than its left neighbour."""
    small = resize(grey(image), side, side + 1)
    return np.packbits(small[:, 1:] > small[:, :-1] + 1e-9).tobytes().hex()


def npy_bytes(a: np.ndarray) -> bytes:
    """An array in the NPY format, version 1.0."""
    shape = f"({', '.join(map(str, a.shape))}{',' if a.ndim == 1 else ''})"
    head = f"{{'descr': '{np.lib.format.dtype_to_descr(a.dtype)}', 'fortran_order': False, 'shape': {shape}, }}".encode()
    pad = -(len(head) + 11) % 64
    return b"\x93NUMPY\x01\x00" + struct.pack("<H", len(head) + pad + 1) + head + b" " * pad + b"\n" + np.ascontiguousarray(a).tobytes()


def read_npy(data: bytes, at: int = 0) -> tuple[np.ndarray, int]:
    """The array that begins at an offset, and the offset behind it."""
    if data[at : at + 8] != b"\x93NUMPY\x01\x00":
        raise ValueError("not NPY 1.0")
    size = struct.unpack_from("<H", data, at + 8)[0]
    head = data[at + 10 : at + 10 + size].decode("latin1")
    dtype = np.dtype(re.search(r"'descr': '([^']+)'", head)[1])
    shape = tuple(int(x) for x in re.search(r"'shape': \(([^)]*)\)", head)[1].split(",") if x.strip())
    n, start = int(np.prod(shape)), at + 10 + size
    return np.frombuffer(data, dtype, n, start).reshape(shape), start + n * dtype.itemsize


def tiles(image: np.ndarray, height: int, width: int) -> Iterator[tuple[int, int, bytes]]:
    """(row, column, NPY bytes) of every tile, edge tiles smaller, in row order."""
    for y in range(0, image.shape[0], height):
        for x in range(0, image.shape[1], width):
            yield y, x, npy_bytes(image[y : y + height, x : x + width])


def untile(parts: list[tuple[int, int, bytes]]) -> np.ndarray:
    """The image its tiles make."""
    read = [(y, x, read_npy(b)[0]) for y, x, b in parts]
    h, w = max(y + a.shape[0] for y, x, a in read), max(x + a.shape[1] for y, x, a in read)
    out = np.zeros((h, w, *read[0][2].shape[2:]), read[0][2].dtype)
    for y, x, a in read:
        out[y : y + a.shape[0], x : x + a.shape[1]] = a
    return out


def media_tiles(images: DataFrame, id_col: str, bytes_col: str, tile: int = 256) -> DataFrame:
    """One row per tile: id, tile_y, tile_x, npy, and the image's height, width and difference_hash."""
    kind = images.schema[id_col].dataType

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 64):
            rows = []
            for key, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                try:
                    image = decode(data or b"")
                    rows += [(key, y, x, t, image.shape[0], image.shape[1], difference_hash(image)) for y, x, t in tiles(image, tile, tile)]
                except (ValueError, IndexError, struct.error):
                    rows.append((key, None, None, None, None, None, None))
            cols = list(zip(*rows)) if rows else [[]] * 7
            kinds = [b.schema.field(0).type, pa.int32(), pa.int32(), pa.binary(), pa.int32(), pa.int32(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, kinds)], names=["id", "tile_y", "tile_x", "npy", "height", "width", "difference_hash"])

    return images.select(images[id_col].alias("id"), images[bytes_col].alias("data")).mapInArrow(
        run, f"id {kind.simpleString()}, tile_y int, tile_x int, npy binary, height int, width int, difference_hash string"
    )


def write_tiles(tiled: DataFrame, root: str) -> DataFrame:
    """Write every tile as an NPY file below a shared path; (id, tile_y, tile_x, path) of what was written.

    Names are fixed by id and place, so a retried task rewrites the same files.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, top = open_fs(root)
        fs.create_dir(top, recursive=True)
        for b in batches:
            b = b.filter(b.column("npy").is_valid())
            names = [f"{i}-{y}-{x}.npy" for i, y, x in zip(*(b.column(c).to_pylist() for c in ("id", "tile_y", "tile_x")))]
            for name, data in zip(names, b.column("npy").to_pylist()):
                with fs.open_output_stream(f"{top}/{name}") as f:
                    f.write(data)
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("tile_y"), b.column("tile_x"), pa.array([f"{root}/{n}" for n in names], pa.string())], names=["id", "tile_y", "tile_x", "path"])

    kind = tiled.schema["id"].dataType.simpleString()
    return tiled.mapInArrow(run, f"id {kind}, tile_y int, tile_x int, path string")


def _carry(data: bytes) -> tuple:
    """A text through the operator: bytes to PGM, decoded, tiled to NPY, read back."""
    payload = data + bytes(-len(data) % WIDTH if data else WIDTH)
    image = decode(encode_pgm(np.frombuffer(payload, np.uint8).reshape(-1, WIDTH)))
    stored = b"".join(t for _, _, t in tiles(image, TILE, WIDTH))
    at, parts = 0, []
    while at < len(stored):
        part, at = read_npy(stored, at)
        parts.append(part)
    back = np.concatenate(parts)
    raw = back.tobytes()
    return len(data), len(raw), hashlib.sha256(raw).hexdigest(), zlib.crc32(raw[-64:]), len(stored), hashlib.sha256(stored).hexdigest(), difference_hash(back), len(parts)


def op2_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text as an 8-bit image of 64 columns in NPY tiles, with digests of what is read back."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "n_tiles"]
        kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()]
        for b in slices(batches):
            cols = zip(*map(_carry, utf8(b, "text")))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), *[pa.array(list(c), k) for c, k in zip(cols, kinds)]], names=names)

    docs = table(spark, sf_dir, "documents").selectExpr("cast(doc_id as long) doc_id", "text")
    return docs.mapInArrow(run, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_tiles long")
