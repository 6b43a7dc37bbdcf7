"""Media columns: Netpbm and BMP pictures decoded to numpy arrays, resized by area with an integral
image, and stored as NPY tiles beside a difference hash.

``decode_pictures`` treats a binary column: one row of measures, tiles, thumbnail and hash for every row.  A null or
broken picture (unknown kind, short or wrong header, samples missing, no pixels) gives nulls and the reason in
``error``; it never fails the job.

``store_documents`` carries arbitrary bytes through the same path: the UTF-8 bytes of a text, zero-padded
to a positive multiple of 64, become the grey samples of a 64-column picture.  A null or empty text is one
row of 64 zero samples.  Equal texts give equal results; repeated rows give repeated rows; a text of any length
is treated tile by tile (``TILE_ROWS`` rows), and the integral image is accumulated over tiles, so what is held
beside the text is one tile.
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
from pyspark.sql import functions as F

from farspan.llm.storage import lean_batches, texts
from farspan.llm.textbatch import all_chunks

COLUMNS = 64
TILE_ROWS = 4096
_TOKEN = re.compile(rb"(?:\s|#[^\n]*\n)*([^\s#]+)")


def encode_pgm(picture: np.ndarray) -> bytes:
    height, width = picture.shape
    return b"P5\n%d %d\n255\n" % (width, height) + picture.tobytes()


def decode_netpbm(raw: bytes) -> np.ndarray:
    """P1 to P6 as uint8 or uint16 samples: (rows, columns), or (rows, columns, 3) for colour."""
    kind, at, fields = raw[:2], 2, []
    if not re.fullmatch(rb"P[1-6]", kind):
        raise ValueError("not a Netpbm picture")
    for _ in range(2 if kind in (b"P1", b"P4") else 3):
        m = _TOKEN.match(raw, at)
        if m is None:
            raise ValueError("Netpbm header ends early")
        fields.append(int(m[1]))
        at = m.end()
    width, height = fields[:2]
    if width < 1 or height < 1 or (len(fields) > 2 and not 0 < fields[2] < 65_536):
        raise ValueError("Netpbm header out of range")
    planes = 3 if kind in (b"P3", b"P6") else 1
    most = fields[2] if len(fields) > 2 else 1
    n = width * height * planes
    if kind == b"P1":
        body = re.sub(rb"#[^\n]*\n?", b"", raw[at:])
        flat = 255 * (1 - (np.frombuffer(re.sub(rb"\s", b"", body), np.uint8)[:n] - 48))
        flat = flat.astype(np.uint8)
    elif kind in (b"P2", b"P3"):
        body = re.sub(rb"#[^\n]*\n?", b"", raw[at:])
        flat = np.array(body.split()[:n], dtype=np.int64).astype(np.uint8 if most < 256 else np.uint16)
    elif kind == b"P4":
        row = (width + 7) // 8
        bits = np.unpackbits(np.frombuffer(raw, np.uint8, row * height, at + 1).reshape(height, row), axis=1)[:, :width]
        flat = (255 * (1 - bits)).astype(np.uint8).ravel()
    else:
        flat = np.frombuffer(raw, np.uint8 if most < 256 else ">u2", n, at + 1)
        flat = flat if most < 256 else flat.astype(np.uint16)
    if len(flat) != n:
        raise ValueError("Netpbm samples end early")
    return flat.reshape((height, width, 3) if planes == 3 else (height, width))


def encode_bmp(picture: np.ndarray) -> bytes:
    """8-bit grey (with a grey palette) or 24-bit colour, uncompressed, bottom row first."""
    height, width = picture.shape[:2]
    grey = picture.ndim == 2
    palette = b"".join(bytes((i, i, i, 0)) for i in range(256)) if grey else b""
    row = width * (1 if grey else 3)
    lines = np.zeros((height, (row + 3) // 4 * 4), np.uint8)
    lines[:, :row] = (picture if grey else picture[:, :, ::-1]).reshape(height, row)[::-1]
    start = 54 + len(palette)
    head = struct.pack("<2sIHHI", b"BM", start + lines.size, 0, 0, start)
    info = struct.pack("<IiiHHIIiiII", 40, width, height, 1, 8 if grey else 24, 0, lines.size, 2835, 2835, 256 if grey else 0, 0)
    return head + info + palette + lines.tobytes()


def decode_bmp(raw: bytes) -> np.ndarray:
    """Uncompressed 8-, 24- and 32-bit pictures, either row order; a grey palette gives a grey array."""
    if raw[:2] != b"BM":
        raise ValueError("not a BMP picture")
    start, size, width, height = struct.unpack_from("<IIii", raw, 10)
    depth, packing = struct.unpack_from("<HI", raw, 28)
    used = struct.unpack_from("<I", raw, 46)[0]
    if packing or depth not in (8, 24, 32):
        raise ValueError(f"BMP with {depth} bits and packing {packing} isn't read")
    if width < 1 or height == 0:
        raise ValueError("picture without pixels")
    rows, stride = abs(height), (width * depth // 8 + 3) // 4 * 4
    body = np.frombuffer(raw, np.uint8, rows * stride, start).reshape(rows, stride)
    body = body if height < 0 else body[::-1]
    if depth == 8:
        palette = np.frombuffer(raw, np.uint8, 4 * (used or 256), 14 + size).reshape(-1, 4)
        colours = palette[body[:, :width]][:, :, 2::-1]
        grey = (palette[:, 0] == palette[:, 1]).all() and (palette[:, 1] == palette[:, 2]).all()
        return np.ascontiguousarray(colours[:, :, 0] if grey else colours)
    return np.ascontiguousarray(body[:, : width * depth // 8].reshape(rows, width, depth // 8)[:, :, 2::-1])


def decode(raw: bytes) -> np.ndarray:
    return decode_bmp(raw) if raw[:2] == b"BM" else decode_netpbm(raw)


def _at_edges(table: np.ndarray, edges: np.ndarray) -> np.ndarray:
    """Rows of a running sum (its first row is 0) at fractional places."""
    low = np.minimum(edges.astype(np.int64), len(table) - 2)
    return table[low] + (edges - low)[:, None] * (table[low + 1] - table[low])


class AreaResize:
    """Mean of the exact (fractional) source area under each target cell, by an integral image that is accumulated
    over blocks of rows: held are the sums at the target's edges and one block."""

    def __init__(self, height: int, width: int, rows: int, columns: int):
        self.shape = (height, width, rows, columns)
        self.edges, self.across = np.linspace(0, height, rows + 1), np.linspace(0, width, columns + 1)
        self.found = np.zeros((rows + 1, columns))
        self.total = np.zeros(columns)
        self.seen = 0

    def add(self, block: np.ndarray) -> None:
        height, width = block.shape
        along = np.zeros((width + 1, height))
        np.cumsum(block.T, axis=0, dtype=np.float64, out=along[1:])
        table = np.zeros((height + 1, len(self.total)))
        np.cumsum(np.diff(_at_edges(along, self.across), axis=0).T, axis=0, out=table[1:])
        table += self.total
        inside = (self.edges > self.seen) & (self.edges <= self.seen + height)
        self.found[inside] = _at_edges(table, self.edges[inside] - self.seen)
        self.total, self.seen = table[-1], self.seen + height

    def result(self) -> np.ndarray:
        height, width, rows, columns = self.shape
        return np.diff(self.found, axis=0) * (rows * columns / (height * width))


def area_resize(picture: np.ndarray, rows: int, columns: int) -> np.ndarray:
    resize = AreaResize(*picture.shape, rows, columns)
    for a in range(0, len(picture), TILE_ROWS):
        resize.add(picture[a : a + TILE_ROWS])
    return resize.result()


def _rising(cells: np.ndarray) -> str:
    return np.packbits(cells[:, 1:] > cells[:, :-1] + 1e-9).tobytes().hex()


def difference_hash(picture: np.ndarray) -> str:
    """64 bits as 16 hex digits: does brightness rise from a cell to its right neighbour, on 8 x 9 cells."""
    resize = AreaResize(*picture.shape[:2], 8, 9)
    for a in range(0, len(picture), TILE_ROWS):
        block = picture[a : a + TILE_ROWS]
        resize.add(block if block.ndim == 2 else block.mean(axis=2))
    return _rising(resize.result())


def thumbnail(picture: np.ndarray, rows: int, columns: int) -> np.ndarray:
    """Area-resized samples of the picture's own type."""
    planes = picture[:, :, None] if picture.ndim == 2 else picture
    small = np.stack([area_resize(planes[:, :, p], rows, columns) for p in range(planes.shape[2])], axis=2)
    out = np.rint(small).astype(picture.dtype)
    return out[:, :, 0] if picture.ndim == 2 else out


def to_tiles(picture: np.ndarray, tile_rows: int = TILE_ROWS) -> list[bytes]:
    tiles = []
    for a in range(0, max(1, len(picture)), tile_rows):
        out = io.BytesIO()
        np.lib.format.write_array(out, np.ascontiguousarray(picture[a : a + tile_rows]), version=(1, 0), allow_pickle=False)
        tiles.append(out.getvalue())
    return tiles


def from_tiles(tiles: list[bytes]) -> np.ndarray:
    parts = [np.lib.format.read_array(io.BytesIO(t), allow_pickle=False) for t in tiles]
    return parts[0] if len(parts) == 1 else np.concatenate(parts)


MEDIA_SCHEMA = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("feature", pa.string())])
SPARK_SCHEMA = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def _stored(raw: memoryview, keep: bool) -> tuple:
    """Measures of the bytes as a 64-column grey picture, through the Netpbm form, NPY tiles, and back."""
    n = len(raw)
    size = max(COLUMNS, -(-n // COLUMNS) * COLUMNS)
    payload, media, media_bytes, tiles, tail = hashlib.sha256(), hashlib.sha256(), 0, [], b""
    resize = AreaResize(size // COLUMNS, COLUMNS, 8, 9)
    for a in range(0, size, TILE_ROWS * COLUMNS):
        b = min(size, a + TILE_ROWS * COLUMNS)
        part = bytes(raw[a : min(b, n)])
        picture = decode_netpbm(encode_pgm(np.frombuffer(part + bytes(b - a - len(part)), np.uint8).reshape(-1, COLUMNS)))
        (tile,) = to_tiles(picture)
        back = from_tiles([tile])
        samples = back.tobytes()
        payload.update(samples)
        media.update(tile)
        media_bytes, tail = media_bytes + len(tile), samples[-COLUMNS:]
        resize.add(back)
        if keep:
            tiles.append(tile)
    row = (n, size, payload.hexdigest(), zlib.crc32(tail), media_bytes, media.hexdigest(), _rising(resize.result()))
    return (*row, tiles) if keep else row


PICTURES = "id long, height long, width long, channels int, bits int, media_bytes long, media_sha256 string, feature string, thumbnail binary, tiles array<binary>, error string"


def _decoded(raw: bytes | None, rows: int, columns: int, keep: bool) -> tuple:
    if raw is None:
        return (None,) * 9 + ("no picture",)
    try:
        picture = decode(raw)
        if 0 in picture.shape:
            raise ValueError("picture without pixels")
    except (ValueError, IndexError, TypeError, OverflowError, struct.error) as e:
        return (None,) * 9 + (str(e) or type(e).__name__,)
    tiles = to_tiles(picture)
    (small,) = to_tiles(thumbnail(picture, rows, columns), max(rows, 1))
    digest = hashlib.sha256(b"".join(tiles)).hexdigest()
    channels = 1 if picture.ndim == 2 else picture.shape[2]
    return (*picture.shape[:2], channels, 8 * picture.itemsize, sum(map(len, tiles)), digest, difference_hash(picture), small, tiles if keep else None, None)


def decode_pictures(df: DataFrame, id_col: str, media_col: str, rows: int = 32, columns: int = 32, with_tiles: bool = True) -> DataFrame:
    """One row (PICTURES) per row of df: its picture's measures, NPY tiles, NPY thumbnail of rows x columns and difference
    hash, or the error.  At most one picture is decoded at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.string(), pa.string(), pa.binary(), pa.list_(pa.binary()), pa.string()]
        names = [x.split()[0] for x in PICTURES.split(", ")]
        for batch in batches:
            for i in range(batch.num_rows):
                out = (batch.column(0)[i].as_py(), *_decoded(batch.column(1)[i].as_py(), rows, columns, with_tiles))
                yield pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip(out, kinds, strict=True)], names=names)

    return lean_batches(df).select(F.col(id_col).cast("long").alias("id"), F.col(media_col).cast("binary").alias("media")).mapInArrow(run, PICTURES)


def store_documents(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", with_tiles: bool = False) -> DataFrame:
    """One row per row of df; ``with_tiles`` adds the stored NPY tiles themselves as array<binary>."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = MEDIA_SCHEMA.append(pa.field("tiles", pa.list_(pa.binary()))) if with_tiles else MEDIA_SCHEMA
        for part, chunk in all_chunks(batches):
            whole = memoryview(chunk.data)
            rows = [_stored(whole[a:b], with_tiles) for a, b in zip(chunk.off[:-1].tolist(), chunk.off[1:].tolist(), strict=True)]
            values = [part.column(0), *map(list, zip(*rows, strict=True))]
            yield pa.RecordBatch.from_arrays([pa.array(v, f.type) if isinstance(v, list) else v for v, f in zip(values, schema, strict=True)], schema=schema)

    return texts(df, id_col, text_col).mapInArrow(run, SPARK_SCHEMA + (", tiles array<binary>" if with_tiles else ""))
