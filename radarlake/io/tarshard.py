"""Tar shards of keyed samples: a sample's members stand next to each other, named key.member.

`spark.dataSource.register(TarShards)` gives the format "tarshard": rows (key, members:
map of name to bytes). A task writes one file under a temporary name, and the commit
renames it; a task reads one file from its start to its end. The folder must be one that
the workers can open.
"""

from __future__ import annotations

import io
import os
import random
import tarfile
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage
from pyspark.sql.types import StructType

SCHEMA = "key string, members map<string, binary>"


@dataclass
class _Written(WriterCommitMessage):
    part: str | None
    name: str | None


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, folder: str, members: set[str] | None):
        self.folder, self.members = folder, members

    def partitions(self) -> list[InputPartition]:
        names = sorted(n for n in os.listdir(self.folder) if n.endswith(".tar"))
        return [_File(os.path.join(self.folder, n)) for n in names]

    def read(self, partition: _File) -> Iterator[tuple]:
        key, members = None, {}
        if partition is None:
            return
        with tarfile.open(partition.path, "r|") as tar:
            for item in tar:
                k, dot, member = item.name.partition(".")
                if not dot:
                    raise ValueError(f"{item.name}: a member needs a key and a name")
                if k != key and key is not None:
                    yield key, members
                    members = {}
                key = k
                if self.members is None or member in self.members:
                    members[member] = tar.extractfile(item).read()
        if key is not None:
            yield key, members


class _Writer(DataSourceWriter):
    def __init__(self, folder: str):
        self.folder = folder

    def write(self, iterator: Iterator) -> _Written:
        os.makedirs(self.folder, exist_ok=True)
        name, tar = uuid.uuid4().hex, None
        part = os.path.join(self.folder, f".{name}.part")
        for row in iterator:
            if row["key"] is None or "." in row["key"]:
                raise ValueError(f"{row['key']}: a key holds no dot")
            tar = tar or tarfile.open(part, "w")
            for member in sorted(row["members"] or {}):
                data = bytes(row["members"][member])
                info = tarfile.TarInfo(f"{row['key']}.{member}")
                info.size = len(data)
                tar.addfile(info, io.BytesIO(data))
        if tar is None:
            return _Written(None, None)
        tar.close()
        return _Written(part, os.path.join(self.folder, f"shard-{name}.tar"))

    def commit(self, messages: list) -> None:
        for m in messages:
            if m is not None and m.part:
                os.replace(m.part, m.name)

    def abort(self, messages: list) -> None:
        for m in messages:
            if m is not None and m.part and os.path.exists(m.part):
                os.remove(m.part)


def read_shuffled(spark: SparkSession, folder: str, seed: int, buffer: int = 1024) -> DataFrame:
    """Samples of all shards in a shuffled order without sorting: shards are dealt out by a seeded hash of their name, and each task
    lets samples pass through a buffer from which a seeded draw picks the next one. Every sample comes once.
    """
    from pyspark.sql import functions as F

    names = spark.createDataFrame([(os.path.join(folder, n),) for n in sorted(os.listdir(folder)) if n.endswith(".tar")], "path string")
    parts = max(1, min(names.count(), int(spark.conf.get("spark.sql.shuffle.partitions"))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader, held = _Reader(folder, None), []
        kind = pa.map_(pa.string(), pa.binary())

        def batch(rows: list) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([k for k, _ in rows], pa.string()), pa.array([list(m.items()) for _, m in rows], kind)], names=["key", "members"])

        draw = None
        for b in batches:
            for path in b.column(b.schema.names.index("path")).to_pylist():
                draw = draw or random.Random(f"{seed}-{os.path.basename(path)}")
                for sample in reader.read(_File(path)):
                    held.append(sample)
                    if len(held) >= buffer:
                        k = draw.randrange(len(held))
                        held[k], held[-1] = held[-1], held[k]
                        yield batch([held.pop()])
        if held:
            draw.shuffle(held)
            for a in range(0, len(held), 64):
                yield batch(held[a : a + 64])

    order = F.md5(F.concat(F.lit(f"{seed}-"), F.element_at(F.split("path", "/"), -1)))
    dealt = names.withColumn("h", order).repartition(parts, "h").sortWithinPartitions("h")
    return dealt.select("path").mapInArrow(run, SCHEMA)


class TarShards(DataSource):
    """Options: `path`, and `members`, a comma list of the members to read."""

    @classmethod
    def name(cls) -> str:
        return "tarshard"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema: StructType) -> DataSourceReader:
        wanted = self.options.get("members")
        return _Reader(self.options["path"], set(wanted.split(",")) if wanted else None)

    def writer(self, schema: StructType, overwrite: bool) -> DataSourceWriter:
        return _Writer(self.options["path"])
