"""Sorted 64-bit keys as binary values: what a task sends to a bucket, and files in the shared folder.

A task adds up before it sends: one binary value holds a bucket's sorted distinct keys as
byte planes of their differences, which the shuffle's compression shrinks to the few
planes that hold anything.
"""

from __future__ import annotations

import json
import os
import tempfile
import uuid
from functools import lru_cache

import numpy as np


def pack(keys: np.ndarray) -> bytes:
    """Sorted keys of 64 bits as planes of their differences."""
    step = np.diff(keys.astype(np.uint64), prepend=np.uint64(0))
    return np.ascontiguousarray(step.astype("<u8").view(np.uint8).reshape(-1, 8).T).tobytes()


def unpack(raw: bytes) -> np.ndarray:
    planes = np.frombuffer(raw, np.uint8).reshape(8, -1)
    return np.cumsum(np.ascontiguousarray(planes.T).view("<u8").reshape(-1).astype(np.uint64), dtype=np.uint64)


def planes(values: np.ndarray) -> bytes:
    """Values of 64 bits in any order as byte planes."""
    return np.ascontiguousarray(values.astype("<i8").view(np.uint8).reshape(-1, 8).T).tobytes()


def unplanes(raw: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(8, -1).T).view("<i8").reshape(-1).astype(np.int64)


def values(batch, *names: str):
    """Rows of the named columns of a record batch; binary values are views of the batch's memory."""
    import pyarrow as pa

    columns = [batch.column(batch.schema.get_field_index(n)) for n in names]
    binary = [pa.types.is_binary(c.type) for c in columns]
    for i in range(batch.num_rows):
        yield tuple(memoryview(c[i].as_buffer()) if b else c[i].as_py() for c, b in zip(columns, binary, strict=True))


def merge(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct keys and their summed counts (rows of counts for two axes)."""
    if not keys:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    k, c = np.concatenate(keys), np.concatenate(counts)
    order = np.argsort(k, kind="stable")
    k, c = k[order], c[order]
    first = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]])) if len(k) else np.zeros(0, np.int64)
    return k[first], np.add.reduceat(c, first, axis=0) if len(k) else c


def range_bucket(hashed: np.ndarray, buckets: int) -> np.ndarray:
    """The part, of equal parts of the 64-bit range, that a hash lies in."""
    return ((hashed >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)).astype(np.int64)


def put_file(path: str, data: np.ndarray) -> None:
    """Writes an array to a URI of the shared folder under its name when it is whole; a repeated task replaces it."""
    from pyarrow import fs

    where, inner = fs.FileSystem.from_uri(path)
    part = f"{inner}.{uuid.uuid4().hex}"
    where.create_dir(os.path.dirname(inner), recursive=True)
    with where.open_output_stream(part) as f:
        f.write(memoryview(np.ascontiguousarray(data)).cast("B") if data.size else b"")
    where.move(part, inner)


def put_bundle(path: str, **arrays: np.ndarray) -> None:
    """Several arrays as one file, each from a multiple of eight bytes on, after a list of them."""
    listed, at, parts = {}, 0, []
    for name, a in arrays.items():
        raw = np.ascontiguousarray(a).view(np.uint8).reshape(-1)
        listed[name] = (a.dtype.str, at, len(raw))
        parts += [raw, np.zeros(-len(raw) % 8, np.uint8)]
        at += len(raw) + -len(raw) % 8
    head = json.dumps(listed).encode()
    head += b" " * (-len(head) % 8)
    put_file(path, np.concatenate([np.frombuffer(len(head).to_bytes(8, "little") + head, np.uint8), *parts]))


@lru_cache(maxsize=1 << 15)
def map_bundle(path: str) -> dict[str, np.ndarray]:
    """The arrays of a file of `put_bundle` as views of its memory map; none where there is no such file."""
    try:
        raw = np.asarray(map_file(path, "u1"))
    except FileNotFoundError:
        return {}
    n = 8 + int.from_bytes(raw[:8].tobytes(), "little")
    return {name: raw[n + at : n + at + size].view(kind) for name, (kind, at, size) in json.loads(raw[8:n].tobytes()).items()}


@lru_cache(maxsize=1 << 15)
def map_file(path: str, dtype: str) -> np.ndarray:
    """A file of the shared folder as a memory map; one that isn't on a mounted disk is fetched once by the worker."""
    from pyarrow import fs

    where, inner = fs.FileSystem.from_uri(path)
    if where.type_name == "local":
        return np.memmap(inner, dtype, "r") if os.path.getsize(inner) else np.zeros(0, dtype)
    # the copy has no name, so it goes with the worker
    with where.open_input_stream(inner) as source, tempfile.TemporaryFile() as f:
        while block := source.read(1 << 22):
            f.write(block)
        f.flush()
        return np.memmap(f, dtype, "r") if f.tell() else np.zeros(0, dtype)


def search(keys: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Places of the wanted keys in a sorted array, -1 for those that aren't there."""
    if not len(keys):
        return np.full(len(wanted), -1, np.int64)
    at = np.searchsorted(keys, wanted)
    at[at == len(keys)] = 0
    return np.where(keys[at] == wanted, at, -1)
