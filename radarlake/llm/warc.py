"""WARC records as a chunk table: record id and chunk number, so that no payload has to be one value.

`write` serialises each page as a WARC/1.1 record and stores the bytes in chunks, each
with the running SHA-1 of the record's payload up to its end; `read` streams a record's
chunks in order, parses the header from the first one, checks each running digest, and
never joins the chunks. Records of one chunk are read where they lie; only longer ones
are dealt out by record id. `export` joins the stored bytes to archive files.

Null payloads count as empty. Repeated page ids give repeated records. Ties of equal
payloads go to the smallest page id; a page without an id is never the first one, and its
record names no page.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from radarlake.llm.common import partitions, scratch

CHUNK = 256 << 10
_STORED = "record_id string, copy long, page_id long, chunk_no int, chunks int, data binary, payload_sha1 binary"
_READ = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, record_id string, chunks long"


def _digest(sha1: bytes) -> str:
    return base64.b32encode(sha1).decode()


def _record_id(page: int | None, copy: int) -> str:
    return f"urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'radarlake:page:{page}:{copy}')}"


def _header(page: int | None, url: str | None, refers: int | None, digest: str, payload: int, record: str) -> tuple[bytes, bytes]:
    """The WARC header and the block's own header before the payload."""
    block = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {payload}\r\n\r\n".encode()
    kind = "response" if refers is None else "revisit"
    lines = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <{record}>", "WARC-Date: 1970-01-01T00:00:00Z"]
    if url:
        lines.append("WARC-Target-URI: " + " ".join(url.split()))
    if page is not None:
        lines.append(f"WARC-Page-ID: {page}")
    lines += [f"WARC-Payload-Digest: sha1:{digest}", f"WARC-Payload-Length: {payload}"]
    if refers is not None:
        lines += [f"WARC-Refers-To: <{_record_id(refers, 0)}>", f"WARC-Refers-To-Page: {refers}", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    length = len(block) + (payload if refers is None else 0)
    lines += ["Content-Type: application/http; msgtype=response", f"Content-Length: {length}", "", ""]
    return "\r\n".join(lines).encode(), block


def _serialise(chunk: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        copy = TaskContext.get().partitionId() << 33
        schema = pa.schema([("record_id", pa.string()), ("copy", pa.int64()), ("page_id", pa.int64()), ("chunk_no", pa.int32()), ("chunks", pa.int32()), ("data", pa.binary()), ("payload_sha1", pa.binary())])
        out: list[tuple] = []
        held = 0

        def batch() -> pa.RecordBatch:
            made = pa.RecordBatch.from_arrays([pa.array(x, t.type) for x, t in zip(zip(*out, strict=True), schema, strict=True)], schema=schema)
            out.clear()
            return made

        for b in batches:
            names = b.schema.names
            page, url, html, first = (b.column(names.index(n)) for n in ("page_id", "url", "payload", "first"))
            for i in range(b.num_rows):
                p, value = page[i].as_py(), html[i]
                payload = memoryview(value.as_buffer()) if value.is_valid else memoryview(b"")
                f = first[i].as_py()
                refers = None if f is None or f == p else f
                record = _record_id(p, 0)
                digest = _digest(hashlib.sha1(payload).digest())
                head, block = _header(p, url[i].as_py(), refers, digest, len(payload), record)
                body = payload if refers is None else memoryview(b"")
                lead = head + block
                running = hashlib.sha1()
                copy += 1
                n = max(1, -(-(len(lead) + len(body) + 4) // chunk))
                for k in range(n):
                    lo, hi = k * chunk, (k + 1) * chunk
                    part = body[max(0, lo - len(lead)) : max(0, hi - len(lead))]
                    running.update(part)
                    end = b"\r\n\r\n"[max(0, lo - len(lead) - len(body)) : max(0, hi - len(lead) - len(body))]
                    out.append((record, copy, p, k, n, b"".join((lead[lo:hi], part, end)), running.digest()))
                    held += len(out[-1][5])
                    if held > 8 << 20:
                        yield batch()
                        held = 0
        if out:
            yield batch()

    return run


def link(pages: DataFrame, least: int = 0, payload: str = "html") -> DataFrame:
    """Pages (page_id, url, payload in UTF-8, first): `first` is the smallest page id of an equal payload of at least `least` bytes.

    Digests are grouped without the payloads, which then move once, by page id and digest, so
    that a payload that many pages share lies in no single task.
    """
    kept = pages.select("page_id", F.col("url") if "url" in pages.columns else F.lit(None).cast("string").alias("url"), F.coalesce(F.col(payload).cast("binary"), F.lit(b"")).alias("payload"))
    keyed = kept.withColumn("sha1", F.unhex(F.sha1("payload"))).withColumn("n", F.octet_length("payload"))
    marks = keyed.select("page_id", "sha1", "n").filter(F.col("n") >= least)
    groups = marks.groupBy("sha1", "n").agg(F.min("page_id").alias("first"), F.count("*").alias("pages")).filter("pages > 1")
    told = marks.join(groups, ["sha1", "n"]).filter("not (page_id <=> first)").select("page_id", "sha1", "first").distinct().toDF("_page", "_sha1", "first")
    return keyed.join(told, keyed["page_id"].eqNullSafe(told["_page"]) & (keyed["sha1"] == told["_sha1"]), "left").select("page_id", "url", "payload", "first")


def write(linked: DataFrame, path: str, chunk: int = CHUNK) -> str:
    """Stores what `link` returns as a chunk table at `path`."""
    linked.mapInArrow(_serialise(chunk), _STORED).write.mode("overwrite").option("compression", "zstd").parquet(path)
    return path


class _Record:
    """One record while its chunks go by: at most a header and a chunk are held."""

    def __init__(self, record: str, chunks: int):
        self.record, self.chunks, self.next, self.head, self.left = record, chunks, 0, b"", None
        self.sha1, self.got, self.fields = hashlib.sha1(), 0, {}

    def feed(self, number: int, data: bytes, running: bytes) -> None:
        if number != self.next:
            raise ValueError(f"{self.record}: chunk {self.next} is missing")
        self.next += 1
        if self.left is None:
            self.head += data
            warc, found, rest = self.head.partition(b"\r\n\r\n")
            if not found or b"\r\n\r\n" not in rest:
                return self._check(running)
            lines = warc.decode().split("\r\n")
            if lines[0] != "WARC/1.1":
                raise ValueError(f"{self.record}: not a WARC record")
            self.fields = dict(x.split(": ", 1) for x in lines[1:])
            block, _, data = rest.partition(b"\r\n\r\n")
            self.left = int(self.fields["Content-Length"]) - len(block) - 4
            self.head = b""
        part = memoryview(data)[: self.left]
        self.left -= len(part)
        self.got += len(part)
        self.sha1.update(part)
        self._check(running)

    def _check(self, running: bytes) -> None:
        if self.sha1.digest() != running:
            raise ValueError(f"{self.record}: the payload differs from the stored digest")

    def row(self) -> tuple:
        f = self.fields
        if self.next != self.chunks or self.left:
            raise ValueError(f"{self.record}: the record is cut off")
        response = f["WARC-Type"] == "response"
        digest = f["WARC-Payload-Digest"].removeprefix("sha1:")
        if response and (digest != _digest(self.sha1.digest()) or self.got != int(f["WARC-Payload-Length"])):
            raise ValueError(f"{self.record}: the payload differs from its header")
        refers = None if response else int(f["WARC-Refers-To-Page"])
        page = f.get("WARC-Page-ID")
        return None if page is None else int(page), int(f["WARC-Payload-Length"]), digest, f["WARC-Type"], refers, self.record, self.chunks


def _parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("record_id", pa.string()), ("chunks", pa.int64())])
    open_record: _Record | None = None
    for b in batches:
        rows = []
        names = b.schema.names
        record, number, chunks, data, running = (b.column(names.index(n)) for n in ("record_id", "chunk_no", "chunks", "data", "payload_sha1"))
        for r, k, n, d, s in zip(record.to_pylist(), number.to_pylist(), chunks.to_pylist(), data, running.to_pylist(), strict=True):
            if open_record is None:
                open_record = _Record(r, n)
            open_record.feed(k, d.as_buffer().to_pybytes(), s)
            if open_record.next == n:
                rows.append(open_record.row())
                open_record = None
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(x, t.type) for x, t in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)
    if open_record is not None:
        raise ValueError(f"{open_record.record}: the record is cut off")


def read(stored: DataFrame) -> DataFrame:
    """A row for each record of a chunk table, its payload checked against both digests; `copy` tells equal record ids apart."""
    short = stored.filter("chunks = 1").mapInArrow(_parse, _READ)
    long = stored.filter("chunks > 1").repartition(partitions(stored.sparkSession), "record_id", "copy").sortWithinPartitions("record_id", "copy", "chunk_no")
    return short.unionByName(long.mapInArrow(_parse, _READ))


def round_trip(pages: DataFrame, least: int = 0, payload: str = "html", chunk: int = CHUNK) -> DataFrame:
    """Writes the pages and reads them back."""
    spark = pages.sparkSession
    return read(spark.read.schema(_STORED).parquet(write(link(pages, least, payload), scratch(spark, "warc"), chunk)))


def export(stored: DataFrame, folder: str, archive_bytes: int = 1 << 30) -> DataFrame:
    """Writes the stored bytes as .warc files below a folder that all workers can open; returns file names and sizes.

    A partition's records go to files of about `archive_bytes`; a file appears under its name when it is whole.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        from pyspark import TaskContext

        os.makedirs(folder, exist_ok=True)
        part, number, handle, names, sizes = TaskContext.get().partitionId(), 0, None, [], []
        for b in batches:
            for number_in, data in zip(b.column(b.schema.names.index("chunk_no")).to_pylist(), b.column(b.schema.names.index("data")), strict=True):
                if handle is None or (number_in == 0 and handle.tell() >= archive_bytes):
                    if handle is not None:
                        handle.close()
                        os.replace(names[-1] + ".part", names[-1])
                    names.append(os.path.join(folder, f"part-{part:05d}-{number:05d}.warc"))
                    sizes.append(0)
                    handle, number = open(names[-1] + ".part", "wb"), number + 1
                sizes[-1] += handle.write(data.as_buffer())
        if handle is not None:
            handle.close()
            os.replace(names[-1] + ".part", names[-1])
        yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(sizes, pa.int64())], names=["file", "bytes"])

    dealt = stored.repartition(partitions(stored.sparkSession), "record_id", "copy").sortWithinPartitions("record_id", "copy", "chunk_no")
    return dealt.mapInArrow(run, "file string, bytes long")
