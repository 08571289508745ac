"""Media columns: bytes kept as PNG images in binary columns, read back with checks, and hashed.

Payloads are stored as 8-bit grey images of a fixed width. The writer emits signature, IHDR, IDAT and
IEND chunks; the reader tests every chunk's CRC, inflates the zlib stream and undoes the row filters
with numpy. The feature is a 64-bit hash of the image's low-frequency cosine coefficients.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql.types import StructType

from spanfocus.session import ship_package

# Fixed values of the PNG format.
SIGNATURE = b"\x89PNG\r\n\x1a\n"
NONE, SUB, UP, AVERAGE, PAETH = 0, 1, 2, 3, 4

WIDTH = 64
#: Side of the reduced image and of the kept corner of its cosine transform.
SIDE, CORNER = 32, 8


def padded(data: bytes, width: int = WIDTH) -> bytes:
    """``data`` with zero bytes up to a positive multiple of ``width``."""
    return data.ljust(max(width, -(-len(data) // width) * width), b"\0")


def _chunk(kind: bytes, body: bytes) -> bytes:
    return struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))


def _filtered(image: np.ndarray, kind: int) -> np.ndarray:
    """Rows after one of the filters NONE, SUB or UP (bytes, modulo 256)."""
    out = image.copy()
    if kind == SUB:
        out[:, 1:] -= image[:, :-1]
    elif kind == UP:
        out[1:] -= image[:-1]
    return out


def encode_png(image: np.ndarray, kind: int | None = None, level: int = 6) -> bytes:
    """An 8-bit grey image as PNG; ``kind`` None takes the filter with the least sum of magnitudes."""
    height, width = image.shape
    if kind is None:
        cost = {k: int(np.abs(_filtered(image, k).view(np.int8).astype(np.int16)).sum()) for k in (NONE, SUB, UP)}
        kind = min(cost, key=lambda k: (cost[k], k))
    rows = np.empty((height, width + 1), np.uint8)
    rows[:, 0] = kind
    rows[:, 1:] = _filtered(image, kind)
    header = struct.pack(">IIBBBBB", width, height, 8, 0, 0, 0, 0)
    return SIGNATURE + _chunk(b"IHDR", header) + _chunk(b"IDAT", zlib.compress(rows.tobytes(), level)) + _chunk(b"IEND", b"")


def png_chunks(data: bytes) -> Iterator[tuple[bytes, bytes]]:
    """(kind, body) of each chunk; ValueError for a wrong signature, length, checksum or missing end."""
    if data[:8] != SIGNATURE:
        raise ValueError("not a PNG: wrong signature")
    at = 8
    while at < len(data):
        if at + 12 > len(data):
            raise ValueError("PNG chunk is cut short")
        (size,) = struct.unpack_from(">I", data, at)
        end = at + 8 + size
        if end + 4 > len(data):
            raise ValueError("PNG chunk is cut short")
        kind, body = data[at + 4 : at + 8], data[at + 8 : end]
        if zlib.crc32(data[at + 4 : end]) != struct.unpack_from(">I", data, end)[0]:
            raise ValueError(f"PNG chunk {kind!r} fails its checksum")
        yield kind, body
        if kind == b"IEND":
            return
        at = end + 4
    raise ValueError("PNG has no end chunk")


def _unfilter(rows: np.ndarray) -> np.ndarray:
    """Pixels from filtered rows; column 0 holds each row's filter. Runs of one filter go together."""
    kinds, image = rows[:, 0], rows[:, 1:].copy()
    if kinds.size and int(kinds.max()) > PAETH:
        raise ValueError("unknown PNG row filter")
    height, width = image.shape
    starts = [0, *(np.flatnonzero(np.diff(kinds)) + 1).tolist(), height]
    for a, b in zip(starts, starts[1:], strict=False):
        kind = int(kinds[a]) if a < height else NONE
        if kind == SUB:
            image[a:b] = np.cumsum(image[a:b], axis=1, dtype=np.uint8)
        elif kind == UP:
            if a:
                image[a] += image[a - 1]
            image[a:b] = np.cumsum(image[a:b], axis=0, dtype=np.uint8)
        elif kind in (AVERAGE, PAETH):
            for y in range(a, b):
                above = image[y - 1].astype(int) if y else np.zeros(width, int)
                row, left, corner = image[y], 0, 0
                for x in range(width):
                    up = int(above[x])
                    if kind == AVERAGE:
                        guess = (left + up) // 2
                    else:
                        near = left + up - corner
                        guess = min((left, up, corner), key=lambda v, near=near: abs(near - v))
                    left = (int(row[x]) + guess) & 255
                    row[x], corner = left, up
    return image


def decode_png(data: bytes) -> np.ndarray:
    """The 8-bit grey image of a PNG; ValueError where a check fails or the format is another one."""
    header, packed = None, []
    for kind, body in png_chunks(data):
        if kind == b"IHDR":
            header = struct.unpack(">IIBBBBB", body)
        elif kind == b"IDAT":
            packed.append(body)
    if header is None or header[2:] != (8, 0, 0, 0, 0):
        raise ValueError("only 8-bit grey PNG without interlace is read")
    width, height = header[:2]
    raw = np.frombuffer(zlib.decompress(b"".join(packed)), np.uint8)
    if raw.size != height * (width + 1):
        raise ValueError("PNG image data has the wrong length")
    return _unfilter(raw.reshape(height, width + 1))


def _cosines(n: int, kept: int) -> np.ndarray:
    k, x = np.arange(kept)[:, None], np.arange(n)[None, :]
    return np.cos(np.pi * k * (2 * x + 1) / (2 * n))


_BASIS = _cosines(SIDE, CORNER)


def _reduced(image: np.ndarray, axis: int) -> np.ndarray:
    """Means of SIDE even slices along ``axis``; a shorter axis repeats its lines."""
    n = image.shape[axis]
    if n <= SIDE:
        return np.take(image, np.arange(SIDE) * n // SIDE, axis=axis).astype(np.float64)
    cuts = np.arange(SIDE + 1) * n // SIDE
    sums = np.add.reduceat(image, cuts[:-1], axis=axis, dtype=np.float64)
    shape = [1, 1]
    shape[axis] = SIDE
    return sums / np.diff(cuts).reshape(shape)


def cosine_hash(image: np.ndarray) -> bytes:
    """Eight bytes: which of the 8 x 8 lowest cosine coefficients exceed their median (the mean term is bit 0)."""
    small = _reduced(_reduced(image, 0), 1)
    low = np.round(_BASIS @ small @ _BASIS.T, 6).ravel()
    return np.packbits(low > np.median(low[1:])).tobytes()


_STORED = "n_bytes bigint, media binary"
_FEATURES = "payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, cosine_hash binary"

Batches = Iterator[pa.RecordBatch]


def _storing(batches: Batches, key: str, width: int, level: int) -> Batches:
    """(key, text) to (key, n_bytes, media), some megabytes at a time."""
    for batch in batches:
        keys, sizes, media, held, start = batch.column(0), [], [], 0, 0
        for i, value in enumerate(batch.column(1)):
            data = (value.as_py() or "").encode()
            stored = encode_png(np.frombuffer(padded(data, width), np.uint8).reshape(-1, width), level=level)
            sizes.append(len(data))
            media.append(stored)
            held += len(stored)
            if held > 4_000_000 or i + 1 == batch.num_rows:
                yield pa.RecordBatch.from_arrays(
                    [keys.slice(start, len(sizes)), pa.array(sizes, pa.int64()), pa.array(media, pa.binary())],
                    names=[key, "n_bytes", "media"],
                )
                sizes, media, held, start = [], [], 0, i + 1
        pa.default_memory_pool().release_unused()


def _features(stored: bytes | None) -> tuple:
    if stored is None:
        return (None,) * 6
    image = decode_png(stored)
    payload = image.tobytes()
    return (
        len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-WIDTH:]),
        len(stored), hashlib.sha256(stored).hexdigest(), cosine_hash(image),
    )


def _reading(batches: Batches, names: list[str]) -> Batches:
    """(carried columns, media) to (carried columns, features)."""
    kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.binary()]
    for batch in batches:
        made = list(zip(*(_features(v.as_py()) for v in batch.column(batch.num_columns - 1)), strict=True)) or [()] * len(kinds)
        arrays = batch.columns[:-1] + [pa.array(c, k) for c, k in zip(made, kinds, strict=True)]
        yield pa.RecordBatch.from_arrays(arrays, names=names)


def _schema(df: DataFrame, keys: list[str], ddl: str) -> StructType:
    return StructType([*df.select(*keys).schema.fields, *StructType.fromDDL(ddl).fields])


def store_png(df: DataFrame, key: str = "doc_id", text: str = "text", width: int = WIDTH, level: int = 6) -> DataFrame:
    """(key, n_bytes, media): every text's UTF-8 bytes, padded with zeros, as a PNG in a binary column.

    Null text counts as empty: one row of zeros. Repeated rows stay; other columns are not read.
    Equal texts give equal images. An empty table gives an empty result.
    """
    ship_package(df.sparkSession)
    return df.select(key, text).mapInArrow(lambda batches: _storing(batches, key, width, level), _schema(df, [key], _STORED))


def read_png(df: DataFrame, key: str = "doc_id", media: str = "media", carry: tuple[str, ...] = ("n_bytes",)) -> DataFrame:
    """Read stored images back: digests of the pixels and of the stored form, and the cosine hash.

    A stored form that fails a check raises; a null one gives null digests.
    """
    ship_package(df.sparkSession)
    schema = _schema(df, [key, *carry], _FEATURES)
    names = schema.fieldNames()
    return df.select(key, *carry, media).mapInArrow(lambda batches: _reading(batches, names), schema)


def store_and_read_png(df: DataFrame, key: str = "doc_id", text: str = "text", width: int = WIDTH, level: int = 6) -> DataFrame:
    """:func:`store_png` and :func:`read_png` in one Python worker: images pass between them in batches."""
    ship_package(df.sparkSession)
    schema = _schema(df, [key], f"n_bytes bigint, {_FEATURES}")
    names = schema.fieldNames()
    return df.select(key, text).mapInArrow(lambda batches: _reading(_storing(batches, key, width, level), names), schema)
