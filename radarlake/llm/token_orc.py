"""Token ids in ORC: stripes of run-length encoded integers, row indexes, Bloom filters on document ids.

`write` deals the documents out by ranges of their id, sorts each range, encodes, and
writes one ORC file a range; each row carries its shard and the ids before it in the
shard, so that global positions need only the shards' totals. Stripes are read in
parallel, and a lookup by id skips files, stripes and row groups by their statistics
and Bloom filters (`lookup`).

Null and empty texts hold the end id alone; repeated ids keep one row each.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from radarlake.llm.common import chunks, partitions, scratch
from radarlake.llm.tokens import encoder, with_end

#: ids as the writer stores them: 32 bits, signed in ORC.
SCHEMA = "doc_id long, shard int, before long, ids array<int>"
OPTIONS = {"orc.bloom.filter.columns": "doc_id", "orc.bloom.filter.fpp": "0.01", "orc.row.index.stride": "1000", "orc.stripe.size": str(16 << 20), "compression": "zstd"}


def _encode(path: str, end: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        shard, before = TaskContext.get().partitionId(), 0
        encode = encoder(path)
        for rows, data, offsets in chunks(batches, "text"):
            ids, at = with_end(*encode.chunk(data, offsets), end)
            lists = pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(ids.view(np.int32)))
            n = rows.num_rows
            yield pa.RecordBatch.from_arrays([rows.column(rows.schema.get_field_index("doc_id")), pa.array(np.full(n, shard, np.int32)), pa.array(before + at[:-1]), lists], names=["doc_id", "shard", "before", "ids"])
            before += int(at[-1])

    return run


def write(docs: DataFrame, path: str, tokenizer: str, end: int, shards: int | None = None) -> str:
    """Writes the ids of `docs` (doc_id, text) to ORC files at `path`, in ascending order of doc_id."""
    sorted_ = docs.select("doc_id", "text").repartitionByRange(shards or partitions(docs.sparkSession), "doc_id").sortWithinPartitions("doc_id")
    sorted_.mapInArrow(_encode(tokenizer, end), SCHEMA).write.mode("overwrite").options(**OPTIONS).orc(path)
    return path


def _checked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        lists = b.column(b.schema.get_field_index("ids"))
        at = np.asarray(lists.offsets)
        raw = memoryview(np.ascontiguousarray(np.asarray(lists.values)).astype("<i4", copy=False)).cast("B")
        crc = [zlib.crc32(raw[4 * x : 4 * y]) for x, y in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
        keep = [b.column(b.schema.get_field_index(n)) for n in ("doc_id", "shard", "before")]
        yield pa.RecordBatch.from_arrays([*keep, pa.array(np.diff(at).astype(np.int64)), pa.array(crc, pa.int64())], names=["doc_id", "shard", "before", "n_tokens", "ids_crc32"])


def stored(spark: SparkSession, path: str) -> DataFrame:
    """The rows of a written folder."""
    return spark.read.schema(SCHEMA).orc(path)


def index(spark: SparkSession, path: str) -> DataFrame:
    """Per document: start in the whole id sequence, n_tokens and the checksum of the ids as read back."""
    rows = stored(spark, path).mapInArrow(_checked, "doc_id long, shard int, before long, n_tokens long, ids_crc32 long")
    # one row a shard; the offsets are a running sum over as many rows as the writer made files
    last = stored(spark, path).select("shard", (F.col("before") + F.size("ids")).alias("tokens")).groupBy("shard").agg(F.max("tokens").alias("tokens"))
    totals = sorted((r["shard"], r["tokens"]) for r in last.collect())
    offsets, seen = [], 0
    for shard, tokens in totals:
        offsets.append((shard, seen))
        seen += tokens
    table = spark.createDataFrame(offsets, "shard int, offset long")
    return rows.join(F.broadcast(table), "shard").select("doc_id", (F.col("offset") + F.col("before")).alias("start"), "n_tokens", "ids_crc32", "shard")


def lookup(spark: SparkSession, path: str, wanted: Column) -> DataFrame:
    """Rows whose doc_id meets a condition; the reader prunes by file, stripe, row group and Bloom filter."""
    return stored(spark, path).filter(wanted)


def round_trip(docs: DataFrame, tokenizer: str, end: int) -> DataFrame:
    spark = docs.sparkSession
    return index(spark, write(docs, scratch(spark, "orc"), tokenizer, end))
