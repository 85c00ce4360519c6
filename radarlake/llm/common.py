"""Helpers shared by the text operators: shared scratch folder, byte chunks of text columns, hashes in numpy.

Nulls count as empty text everywhere. Scratch tables live in the folder that the
session names in ``spark.checkpoint.dir`` and go when the driver ends.
"""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import hashlib
import re
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Text bytes that one numpy step works on; a longer document is a chunk of its own.
CHUNK_BYTES = 1 << 21
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_tables: dict[str, np.ndarray] = {}


def scratch(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder, deleted when the driver's process ends."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = f"file://{tempfile.mkdtemp(prefix='radarlake-')}"
        spark.conf.set("spark.checkpoint.dir", base)
    path = f"{base.rstrip('/')}/radarlake/{name}-{uuid.uuid4().hex}"
    atexit.register(_delete, spark, path)
    return path


def stored(df: DataFrame, name: str) -> DataFrame:
    """The rows written to the shared folder and read again: cuts the lineage and survives lost executors."""
    path = scratch(df.sparkSession, name)
    df.write.option("compression", "zstd").parquet(path)
    read = df.sparkSession.read.schema(df.schema).parquet(path)
    read.stored_at = path
    return read


def release(*done: DataFrame) -> None:
    """Deletes tables of `stored` that nothing will read again."""
    for df in done:
        _delete(df.sparkSession, df.stored_at)


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    if jvm is None or spark.sparkContext._jsc is None:
        return
    try:
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # noqa: BLE001  the gateway may be gone already
        pass


def documents(spark: SparkSession, sf_dir: str, name: str = "documents") -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def unused(df: DataFrame, *names: str) -> list[str]:
    """The names, each with underscores before it until no column of `df` has it (in any case)."""
    taken = {c.lower() for c in df.columns}
    out = []
    for name in names:
        while name.lower() in taken:
            name = f"_{name}"
        out.append(name)
    return out


def named(df: DataFrame) -> list[Column]:
    """All columns of `df` by their names, signs in them included."""
    return [F.col(f"`{c.replace('`', '``')}`") for c in df.columns]


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all rows after each other and the offsets of the rows (one more than rows)."""
    if pa.types.is_null(column.type):
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    column = column.cast(pa.large_binary() if pa.types.is_binary(column.type) else pa.large_string())
    if column.null_count:
        column = pc.fill_null(column, b"" if pa.types.is_large_binary(column.type) else "")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(column.buffers()[2], np.uint8) if column.buffers()[2] is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def chunks(batches: Iterator[pa.RecordBatch], text: str, limit: int = CHUNK_BYTES) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Slices of the batches with at most `limit` bytes of text, or one row, each with its bytes and offsets."""
    for batch in batches:
        if not batch.num_rows:
            continue
        data, offsets = utf8(batch.column(batch.schema.get_field_index(text)))
        a = 0
        while a < batch.num_rows:
            b = max(a + 1, int(np.searchsorted(offsets, offsets[a] + limit, "right")) - 1)
            yield batch.slice(a, b - a), data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
            a = b
    tidy()


def tidy() -> None:
    """Gives freed memory of the worker process back, which it would keep between tasks."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # another C library
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def mix(x: np.ndarray) -> np.ndarray:
    """A finaliser over 64 bits: every bit of the input reaches every bit of the result."""
    x = x ^ (x >> np.uint64(30))
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_tables.get("power", ())) <= n:
        m = 1 << max(16, n.bit_length())
        inverse = np.uint64(pow(int(_BASE), -1, 1 << 64))
        for name, base in (("power", _BASE), ("inverse", inverse)):
            x = np.full(m, base, np.uint64)
            x[0] = 1
            _tables[name] = np.multiply.accumulate(x)
    return _tables["power"], _tables["inverse"]


def prefix_hashes(data: np.ndarray) -> np.ndarray:
    """Prefix polynomial hashes modulo 2**64 of a byte string; entry i covers the first i bytes. Equal ones need a look at the bytes."""
    power, _ = _powers(len(data))
    out = np.zeros(len(data) + 1, np.uint64)
    terms = data.astype(np.uint64)
    terms += np.uint64(1)
    terms *= power[: len(data)]
    np.cumsum(terms, out=out[1:])
    return out


def span_hashes(prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hashes of the byte strings [start, end), the same wherever the string stands."""
    _, inverse = _powers(len(prefix) - 1)
    return mix((prefix[end] - prefix[start]) * inverse[start] + (end - start).astype(np.uint64))


_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Words between ASCII white space: their starts and ends, the row of each, and the lower-cased bytes (A-Z only)."""
    low = _LOWER[data]
    inside = ~_SPACE[data]
    edge = np.zeros(len(data) + 1, bool)
    edge[offsets] = True
    first = inside.copy()
    first[1:] &= ~inside[:-1] | edge[1:-1]
    last = inside.copy()
    last[:-1] &= ~inside[1:] | edge[1:-1]
    start = np.flatnonzero(first)
    end = np.flatnonzero(last) + 1
    row = np.searchsorted(offsets, start, "right") - 1
    return start, end, row, low


#: Two primes under 2**31 and a base for each; bytes hashed at once; strings of over LONG_STRING bytes go by a digest.
_PRIMES, _BASES = (2147483647, 2147483629), (1015568748, 461845907)
HASH_BLOCK, LONG_STRING = 1 << 18, 1 << 15


def _residues(k: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of a base and of its inverse modulo a prime, for the positions of a block."""
    if f"residues {k}" not in _tables:
        p, n = _PRIMES[k], HASH_BLOCK + LONG_STRING + 1
        for name, base in ((f"residues {k}", _BASES[k]), (f"inverse residues {k}", pow(_BASES[k], -1, p))):
            out, done = np.ones(n, np.uint64), 1
            while done < n:
                step = min(done, n - done)
                out[done : done + step] = out[:step] * np.uint64(pow(base, done, p)) % np.uint64(p)
                done += step
            _tables[name] = out
    return _tables[f"residues {k}"], _tables[f"inverse residues {k}"]


def string_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hashes of the byte strings [start, end), starts rising, the same wherever a string stands.

    Prefix polynomials modulo two primes, block by block of HASH_BLOCK; a string of over
    LONG_STRING bytes is hashed by a digest. The modulus isn't a power of two, for which
    short strings of equal hashes are known to any base.
    """
    out = np.zeros(len(start), np.uint64)
    size = end - start
    small = np.flatnonzero(size <= LONG_STRING)
    block = start[small] // HASH_BLOCK
    for a in np.flatnonzero(np.concatenate([[True], block[1:] != block[:-1]])).tolist() if len(small) else []:
        b = int(np.searchsorted(block, block[a], "right"))
        mine = small[a:b]
        first, last = int(start[mine[0]]), int(end[mine].max())
        terms = data[first:last].astype(np.uint64) + np.uint64(1)
        parts = []
        for k, p in enumerate(np.array(_PRIMES, np.uint64)):
            power, inverse = _residues(k)
            prefix = np.zeros(last - first + 1, np.uint64)
            # below 2**9 * 2**31 * 2**19, so nothing is lost
            np.cumsum(terms * power[: last - first], out=prefix[1:])
            parts.append((prefix[end[mine] - first] - prefix[start[mine] - first]) % p * inverse[start[mine] - first] % p)
        out[mine] = mix((parts[0] << np.uint64(32)) + parts[1] + mix(size[mine].astype(np.uint64)))
    for i in np.flatnonzero(size > LONG_STRING).tolist():
        out[i] = int.from_bytes(hashlib.blake2b(data[start[i] : end[i]].tobytes(), digest_size=8).digest(), "little")
    return out


def gather(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The places start, start + 1, ... of each range after each other."""
    return np.repeat(start - (np.cumsum(size) - size), size) + np.arange(size.sum())


def same_bytes(one: np.ndarray, a: np.ndarray, other: np.ndarray, b: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Whether the bytes of `one` from each a and those of `other` from b agree over each size (over 0)."""
    out = np.zeros(len(a), bool)
    turn = np.cumsum(size) >> 21
    edge = np.flatnonzero(np.concatenate([[True], turn[1:] != turn[:-1]])) if len(a) else np.zeros(0, np.int64)
    for x, y in zip(edge.tolist(), [*edge[1:].tolist(), len(a)], strict=False):
        n = size[x:y]
        differ = one[gather(a[x:y], n)] != other[gather(b[x:y], n)]
        out[x:y] = np.add.reduceat(differ, np.cumsum(n) - n) == 0
    return out


def word_hashes(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of the lower-cased words of a chunk and the number of words before each row (one more than rows)."""
    start, end, row, low = words(data, offsets)
    return string_hashes(low, start, end), np.searchsorted(row, np.arange(len(offsets)), "left")


def grams(hashed: np.ndarray, before: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the runs of n words inside each row, and the number of runs before each row."""
    count = np.maximum(np.diff(before) - n + 1, 0)
    total = np.concatenate([[0], np.cumsum(count)])
    at = np.arange(total[-1]) - np.repeat(total[:-1] - before[:-1], count)
    out = np.zeros(len(at), np.uint64)
    for k in range(n):
        out = mix(out * np.uint64(0xD6E8FEB86659FD93) + hashed[at + k])
    return out, total


def binary_array(data: np.ndarray, offsets: np.ndarray) -> pa.Array:
    """A binary column whose rows are the byte ranges of `data` between neighbouring offsets."""
    return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(offsets) - 1, [None, pa.py_buffer(np.ascontiguousarray(offsets, np.int64)), pa.py_buffer(np.ascontiguousarray(data).view(np.uint8))]).cast(pa.binary())


class HashIndex:
    """Numbers 0, 1, ... for 64-bit hashes (0 stands for 1): open addressing, probed for whole arrays at once."""

    def __init__(self, capacity: int):
        self.capacity = capacity
        self.keys = np.zeros(1 << (2 * capacity - 1).bit_length(), np.uint64)
        self.place = np.zeros(len(self.keys), np.int32)
        self.size = 0

    def find(self, hashed: np.ndarray) -> np.ndarray:
        """The numbers of the hashes, -1 for those that aren't in."""
        mask = np.uint64(len(self.keys) - 1)
        hashed = np.maximum(hashed, np.uint64(1))
        slot = hashed & mask
        key = self.keys[slot]
        out = np.where(key == hashed, self.place[slot], -1).astype(np.int64)
        left = np.flatnonzero((key != hashed) & (key != 0))
        slot = (slot[left] + np.uint64(1)) & mask
        while len(left):
            key = self.keys[slot]
            hit = key == hashed[left]
            out[left[hit]] = self.place[slot[hit]]
            go = ~hit & (key != 0)
            left, slot = left[go], (slot[go] + np.uint64(1)) & mask
        return out

    def add(self, hashed: np.ndarray) -> None:
        """Appends distinct hashes that aren't in, in their order."""
        number, mask = np.arange(self.size, self.size + len(hashed)), np.uint64(len(self.keys) - 1)
        self.size += len(hashed)
        left = np.maximum(hashed, np.uint64(1))
        slot = left & mask
        while len(left):
            free = self.keys[slot] == 0
            self.keys[slot[free]] = left[free]
            won = free & (self.keys[slot] == left)
            self.place[slot[won]] = number[won]
            left, number, slot = left[~won], number[~won], (slot[~won] + np.uint64(1)) & mask
