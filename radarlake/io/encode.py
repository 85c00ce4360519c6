"""Image members of a sample: grey PNG files, written and read with the standard library."""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

#: First bytes of every PNG file, a fixed value of the format.
SIGNATURE = b"\x89PNG\r\n\x1a\n"


def _chunk(kind: bytes, data: bytes) -> bytes:
    return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))


def png(image: np.ndarray) -> bytes:
    """An 8-bit grey image (rows, columns) as a PNG file."""
    rows, cols = image.shape
    lines = np.zeros((rows, cols + 1), np.uint8)  # a filter byte, 0 for none, before each line
    lines[:, 1:] = image
    return SIGNATURE + _chunk(b"IHDR", struct.pack(">IIBBBBB", cols, rows, 8, 0, 0, 0, 0)) + _chunk(b"IDAT", zlib.compress(lines.tobytes(), 6)) + _chunk(b"IEND", b"")


def unpng(data: bytes) -> np.ndarray:
    """The image of a file that `png` wrote; damaged files are refused."""
    if data[:8] != SIGNATURE:
        raise ValueError("not a PNG file")
    at, size, body = 8, None, b""
    while at < len(data):
        n, kind = struct.unpack(">I4s", data[at : at + 8])
        part = data[at + 8 : at + 8 + n]
        if len(part) != n or struct.unpack(">I", data[at + 8 + n : at + 12 + n])[0] != zlib.crc32(kind + part):
            raise ValueError(f"{kind!r}: the checksum differs")
        if kind == b"IHDR":
            cols, rows, depth, colour, *_ = struct.unpack(">IIBBBBB", part)
            if (depth, colour) != (8, 0):
                raise ValueError("only 8-bit grey images are read")
            size = rows, cols
        elif kind == b"IDAT":
            body += part
        at += 12 + n
    lines = np.frombuffer(zlib.decompress(body), np.uint8).reshape(size[0], size[1] + 1)
    if lines[:, 0].any():
        raise ValueError("only unfiltered lines are read")
    return lines[:, 1:]


def to_png(pixels: Column, cols: Column) -> Column:
    """A grey PNG of a row's pixels (array of 0 to 255, line after line), with `cols` in a line; null for null."""

    @F.arrow_udf("binary")
    def made(x: pa.Array, n: pa.Array) -> pa.Array:
        return pa.array([None if p is None or not w else png(np.array(p, np.uint8).reshape(-1, w)) for p, w in zip(x.to_pylist(), n.to_pylist(), strict=True)], pa.binary())

    return made(pixels, cols)


def from_png(data: Column) -> Column:
    """Width, height and pixels of a PNG column."""

    @F.arrow_udf("struct<cols: int, rows: int, pixels: array<int>>")
    def read(x: pa.Array) -> pa.Array:
        kind = pa.struct([("cols", pa.int32()), ("rows", pa.int32()), ("pixels", pa.list_(pa.int32()))])
        images = [None if d is None else unpng(d) for d in x.to_pylist()]
        return pa.array([None if i is None else {"cols": i.shape[1], "rows": i.shape[0], "pixels": i.ravel().tolist()} for i in images], kind)

    return read(data)
