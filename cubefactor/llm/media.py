"""Media columns: Netpbm and BMP images as binary columns, decoded to numpy arrays and area-resized.

A document's UTF-8 bytes become the samples of a grey image `WIDTH` samples wide: bytes 255 fill the last
block of `BLOCK` bytes. Images are written in a lossless container (binary or plain Netpbm, or BMP),
stored as a Parquet media table in the shared folder, read back, decoded, shrunk by exact area averages
over an integral image, and written as an NPY tile whose neighbours give a difference hash.

Defined cases: a null or empty text is one block of 255s; texts of any length are kept whole (an image
grows in height); equal texts give equal values; repeated rows and null doc_ids are kept; an empty table
gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import io
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, text_buffer, text_or_empty, written

#: Bytes of a block, and samples in an image row (a block is 24 rows of 24).
BLOCK, WIDTH = 576, 24
#: Rows and columns of the tile whose horizontal neighbours are compared.
TILE = (8, 9)


def encode_pnm(samples: np.ndarray, *, plain: bool = False) -> bytes:
    """Netpbm bytes of 8-bit samples: grey for two dimensions, colour for three; binary unless `plain`."""
    height, width = samples.shape[:2]
    colour = samples.ndim == 3
    kind = (2 if plain else 5) + colour
    head = b"P%d\n%d %d\n255\n" % (kind, width, height)
    if not plain:
        return head + np.ascontiguousarray(samples, np.uint8).tobytes()
    rows = samples.reshape(height, -1)
    return head + b"\n".join(b" ".join(b"%d" % v for v in row) for row in rows) + b"\n"


def decode_pnm(data: bytes) -> np.ndarray:
    """Samples of any of the six Netpbm kinds: bits as 0 and 255, 8-bit or 16-bit grey and colour."""
    kind, at, numbers = data[:2], 2, []
    if kind not in (b"P1", b"P2", b"P3", b"P4", b"P5", b"P6"):
        raise ValueError("not a Netpbm image")
    bits = kind in (b"P1", b"P4")
    while len(numbers) < (2 if bits else 3):
        while data[at : at + 1].isspace() or data[at : at + 1] == b"#":
            at = data.index(b"\n", at) + 1 if data[at : at + 1] == b"#" else at + 1
        stop = at
        while data[stop : stop + 1].isdigit():
            stop += 1
        numbers.append(int(data[at:stop]))
        at = stop
    width, height = numbers[:2]
    most = 1 if bits else numbers[2]
    depth = 3 if kind in (b"P3", b"P6") else 1
    shape = (height, width, 3) if depth == 3 else (height, width)
    if kind == b"P1":
        digits = np.frombuffer(data[at:], np.uint8)
        values = digits[(digits == 48) | (digits == 49)][: width * height] - 48
        return np.where(values.reshape(shape) == 1, 0, 255).astype(np.uint8)
    if kind in (b"P2", b"P3"):
        values = np.array(data[at:].split()[: width * height * depth], np.int64)
        return values.reshape(shape).astype(np.uint8 if most < 256 else np.uint16)
    at += 1
    if kind == b"P4":
        packed = np.frombuffer(data, np.uint8, -(-width // 8) * height, at).reshape(height, -1)
        return np.where(np.unpackbits(packed, axis=1)[:, :width] == 1, 0, 255).astype(np.uint8)
    sample = np.uint8 if most < 256 else np.dtype(">u2")
    return np.frombuffer(data, sample, width * height * depth, at).reshape(shape)


def encode_bmp(samples: np.ndarray) -> bytes:
    """An uncompressed BMP: 8-bit grey with a palette, or 24-bit colour; rows from the bottom, padded to four bytes."""
    height, width = samples.shape[:2]
    colour = samples.ndim == 3
    rows = samples[::-1, :, ::-1] if colour else samples[::-1]
    rows = np.ascontiguousarray(rows, np.uint8).reshape(height, -1)
    body = np.pad(rows, ((0, 0), (0, -rows.shape[1] % 4))).tobytes()
    palette = b"" if colour else np.repeat(np.arange(256, dtype=np.uint8), 4).reshape(256, 4).__mul__(np.array([1, 1, 1, 0], np.uint8)).tobytes()
    start = 54 + len(palette)
    number = lambda value, size: int(value).to_bytes(size, "little")
    head = b"BM" + number(start + len(body), 4) + bytes(4) + number(start, 4)
    info = number(40, 4) + number(width, 4) + number(height, 4) + number(1, 2) + number(24 if colour else 8, 2) + bytes(4) + number(len(body), 4) + number(2835, 4) * 2 + number(0 if colour else 256, 4) + bytes(4)
    return head + info + palette + body


def decode_bmp(data: bytes) -> np.ndarray:
    """Samples of an uncompressed 8-bit, 24-bit or 32-bit BMP, rows from top or bottom."""
    if data[:2] != b"BM":
        raise ValueError("not a BMP image")
    number = lambda at, size, signed=False: int.from_bytes(data[at : at + size], "little", signed=signed)
    start, width, height, bits, packing = number(10, 4), number(18, 4), number(22, 4, True), number(28, 2), number(30, 4)
    if packing != 0 or bits not in (8, 24, 32):
        raise ValueError("only uncompressed 8-, 24- and 32-bit BMP images are read")
    stride = -(-width * bits // 32) * 4
    rows = np.frombuffer(data, np.uint8, stride * abs(height), start).reshape(abs(height), stride)[:, : width * bits // 8]
    rows = rows[::-1] if height > 0 else rows
    if bits == 8:
        used = number(46, 4) or 256
        palette = np.frombuffer(data, np.uint8, used * 4, 14 + number(14, 4)).reshape(used, 4)
        colours = palette[rows]
        grey = (palette[:, 0] == palette[:, 1]).all() and (palette[:, 1] == palette[:, 2]).all()
        return colours[:, :, 0] if grey else colours[:, :, 2::-1]
    return rows.reshape(abs(height), width, bits // 8)[:, :, 2::-1]


def decode(data: bytes) -> np.ndarray:
    return decode_bmp(data) if data[:2] == b"BM" else decode_pnm(data)


def area_resize(samples: np.ndarray, height: int, width: int) -> np.ndarray:
    """Exact area averages of grey samples, from an integral image; edges of cells may cut samples."""
    samples = samples.mean(2) if samples.ndim == 3 else samples
    rows, columns = samples.shape
    integral = np.zeros((rows + 1, columns + 1), np.float64)
    integral[1:, 1:] = samples.cumsum(0, dtype=np.float64).cumsum(1)

    def weights(size: int, parts: int) -> tuple[np.ndarray, np.ndarray]:
        edge = np.arange(parts + 1) * size / parts
        whole = np.minimum(edge.astype(np.int64), size - 1)
        return whole, edge - whole

    row, row_part = weights(rows, height)
    column, column_part = weights(columns, width)
    down = integral[row] * (1 - row_part)[:, None] + integral[row + 1] * row_part[:, None]
    cut = down[:, column] * (1 - column_part) + down[:, column + 1] * column_part
    return np.diff(np.diff(cut, axis=0), axis=1) / (rows / height * columns / width)


def difference_hash(tile: np.ndarray) -> str:
    """64 bits in hex: whether each cell is darker than its right neighbour, row by row."""
    bits = np.round(tile[:, :-1], 6) < np.round(tile[:, 1:], 6)
    return np.packbits(bits.ravel()).tobytes().hex()


def npy_bytes(array: np.ndarray) -> bytes:
    out = io.BytesIO()
    np.save(out, array, allow_pickle=False)
    return out.getvalue()


def payload_of(text: bytes) -> np.ndarray:
    """The bytes and the filling up to a positive multiple of the block, as an image."""
    size = max(-(-len(text) // BLOCK), 1) * BLOCK
    out = np.full(size, 255, np.uint8)
    out[: len(text)] = np.frombuffer(text, np.uint8)
    return out.reshape(-1, WIDTH)


def media_table(docs: DataFrame, container: str = "pgm") -> DataFrame:
    """doc_id, n_bytes and the media column of every row, stored in the shared folder and read back."""
    encode = {"pgm": encode_pnm, "bmp": encode_bmp}[container]

    def render(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches):
            data, offsets = text_buffer(part.column(1))
            raw = data.tobytes()
            media = [encode(payload_of(raw[a:b])) for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(np.diff(offsets)), pa.array(media, pa.binary())], ["doc_id", "n_bytes", "media"])

    drawn = docs.select(F.col("doc_id").cast("long"), text_or_empty().alias("text")).mapInArrow(render, "doc_id long, n_bytes long, media binary")
    return written(drawn, "media", "zstd")


def media_features(media: DataFrame) -> DataFrame:
    """The media table with what its decoded samples give: NPY tile, difference hash and checksums."""

    def describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches, "media"):
            columns: dict[str, list] = {k: [] for k in ("payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "tile_npy")}
            for stored in part.column(2).to_pylist():
                samples = decode(stored)
                payload = samples.tobytes()
                tile = area_resize(samples, *TILE)
                for name, value in zip(columns, (len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(stored), hashlib.sha256(stored).hexdigest(), difference_hash(tile), npy_bytes(np.round(tile).astype(np.uint8))), strict=True):
                    columns[name].append(value)
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *(pa.array(v, pa.int64() if isinstance(v[0], int) else pa.binary() if isinstance(v[0], bytes) else pa.string()) for v in columns.values())], ["doc_id", "n_bytes", *columns])

    return media.select("doc_id", "n_bytes", "media").mapInArrow(describe, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, tile_npy binary")
