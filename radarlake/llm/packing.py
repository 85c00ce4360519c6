"""Hierarchical multi-length packing of token ids into windows.

Each document goes to the tier of the smallest window that holds it (longer ones are
first cut into whole longest windows). From the shortest tier up, whole pieces fill
windows of the tier, largest first; what stays open at a tier's end moves up as
fillers, and gaps of the longest windows are filled with cuts of the shorter tiers'
pieces. The last, unfilled window of a task is cut into windows of powers of two, so
that no window is padded. Windows of one tier form step groups of equal tokens: they are
numbered through over all tasks, so that every group but a tier's last one has STEP_TOKENS.

A task packs the documents that it reads and shuffles nothing: sequence ids hold the
task's number. A null or empty text is its end id alone; repeated ids are packed as
often as they come, and a null id stays null.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from radarlake.llm.common import chunks, stored
from radarlake.llm.tokens import encoder, with_end

TIERS = (64, 128, 256, 512, 1024)
#: Tokens of one step group.
STEP_TOKENS = 1 << 16
#: Rows of 20 bytes that are sent to all workers.
SENT_ROWS = 1 << 20
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, tier int, nth long"


def plan(lengths: list[int], tiers: tuple[int, ...] = TIERS, held: list[list[tuple[int, int, int]]] | None = None, last: bool = True) -> tuple[list[list[tuple[int, int, int]]], list[list[tuple[int, int, int]]]]:
    """Windows, each a list of (document, start, length), and the pieces held back by tier.

    `lengths[i]` are the tokens of document i. Without `last`, pieces that fill no
    window stay for the next call as `held`.
    """
    tiers, top = tuple(sorted(tiers)), max(tiers)
    held = held or [[] for _ in tiers]
    windows: list[list[tuple[int, int, int]]] = []
    for doc, n in enumerate(lengths):
        whole = n // top
        windows.extend([(doc, k * top, top)] for k in range(whole))
        if n % top:
            held[bisect_left(tiers, n % top)].append((doc, whole * top, n % top))
    carried: list[tuple[int, int, int]] = []
    for level, size in enumerate(tiers):
        pieces = sorted(held[level], key=lambda p: -p[2])
        fillers = sorted(carried, key=lambda p: p[2])  # from the end: longest first
        carried, held[level] = [], []
        for piece in pieces:
            gap, window = size - piece[2], [piece]
            while gap and fillers:
                # the longest shorter piece that fits whole, else a cut of the shortest one
                at = bisect_left(fillers, gap + 1, key=lambda p: p[2]) - 1
                if at >= 0:
                    window.append(fillers.pop(at))
                else:
                    doc, start, n = fillers.pop(0)
                    window.append((doc, start, gap))
                    rest = (doc, start + gap, n - gap)
                    fillers.insert(bisect_left(fillers, rest[2], key=lambda p: p[2]), rest)
                gap -= window[-1][2]
            if gap:
                carried.extend(window)
            else:
                windows.append(window)
        carried.extend(fillers)
    # what no tier could close: cut into full longest windows, the rest for the next call
    row: list[tuple[int, int, int]] = []
    room = top
    total = sum(p[2] for p in carried)
    for doc, start, n in carried:
        while n and total >= room:
            cut = min(n, room)
            row.append((doc, start, cut))
            start, n, room, total = start + cut, n - cut, room - cut, total - cut
            if not room:
                windows.append(row)
                row, room = [], top
        if n:
            held[bisect_left(tiers, min(n, top))].append((doc, start, n))
    if last:
        windows.extend(_powers([p for tier in held for p in tier]))
        held = [[] for _ in tiers]
    return windows, held


def _powers(pieces: list[tuple[int, int, int]]) -> list[list[tuple[int, int, int]]]:
    """Windows of falling powers of two that hold just these pieces."""
    total = sum(p[2] for p in pieces)
    sizes = [1 << b for b in range(total.bit_length() - 1, -1, -1) if total >> b & 1]
    out, rest = [], list(reversed(pieces))
    for size in sizes:
        window, room = [], size
        while room:
            doc, start, n = rest.pop()
            cut = min(n, room)
            window.append((doc, start, cut))
            room -= cut
            if cut < n:
                rest.append((doc, start + cut, n - cut))
        out.append(window)
    return out


def _task(path: str, end: int, tiers: tuple[int, ...]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        base = TaskContext.get().partitionId() << 33
        made, steps = 0, dict.fromkeys((1 << b for b in range(max(tiers).bit_length() + 1)), 0)
        encode = encoder(path)
        held: list = []
        known: list[tuple[int, int, memoryview]] = []  # doc_id, tokens, bytes
        for rows, data, offsets in _and_end(chunks(batches, "text")):
            first = len(known)
            if rows is not None:
                ids, at = with_end(*encode.chunk(data, offsets), end)
                raw = memoryview(ids.astype("<u4", copy=False)).cast("B")
                known += [(d, y - x, raw[4 * x : 4 * y]) for d, x, y in zip(rows.column(rows.schema.get_field_index("doc_id")).to_pylist(), at[:-1].tolist(), at[1:].tolist(), strict=True)]
            windows, held = plan([0] * first + [n for _, n, _ in known[first:]], tiers, held, last=rows is None)
            out = []
            for window in windows:
                size = sum(p[2] for p in window)
                tier = 1 << (size - 1).bit_length()
                nth, steps[tier] = steps[tier], steps[tier] + 1
                offset = 0
                for doc, start, n in window:
                    d, tokens, raw = known[doc]
                    out.append((d, start, n, zlib.crc32(raw[4 * start : 4 * (start + n)]), tokens, base + made, offset, tier, nth))
                    offset += n
                made += 1
            # documents that still have held pieces move to the front
            kept = sorted({p[0] for tier in held for p in tier})
            place = {doc: i for i, doc in enumerate(kept)}
            known = [known[doc] if doc < first else (*known[doc][:2], memoryview(bytes(known[doc][2]))) for doc in kept]
            held = [[(place[doc], start, n) for doc, start, n in tier] for tier in held]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int32() if k == 7 else pa.int64()) for k, x in enumerate(zip(*out, strict=True))], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "tier", "nth"])

    return run


def _and_end(items: Iterator) -> Iterator:
    yield from items
    yield None, None, None


def pack(docs: DataFrame, tokenizer: str, end: int, tiers: tuple[int, ...] = TIERS, step_tokens: int = STEP_TOKENS) -> DataFrame:
    """A row per piece: where it stands in its document and in its sequence, with the checksum of its ids, the tier and the step group."""
    return balanced(stored(docs.select("doc_id", "text").mapInArrow(_task(tokenizer, end, tiers), SCHEMA), "pieces"), step_tokens)


def balanced(pieces: DataFrame, step_tokens: int = STEP_TOKENS) -> DataFrame:
    """Pieces with `step_group`, a tier's group of windows with `step_tokens` in all: `nth` windows of a task come after those of the tasks before it.

    A tier's windows all hold the same number of tokens. The table of offsets has a row a task and tier and goes to all workers up to SENT_ROWS.
    """
    task = F.shiftright("sequence_id", 33)
    counts = pieces.groupBy(task.alias("task"), "tier").agg((F.max("nth") + 1).alias("n"))
    before = Window.partitionBy("tier").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    table = stored(counts.select("task", "tier", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("first")), "offsets")
    small = table.count() <= SENT_ROWS
    placed = pieces.withColumn("task", task).join(F.broadcast(table) if small else table, ["task", "tier"])
    group = F.floor((F.col("first") + F.col("nth")) * F.col("tier") / step_tokens).cast("long")
    return placed.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "tier", group.alias("step_group"))


def padding(pieces: DataFrame) -> DataFrame:
    """Sequences, tokens, padded places and pieces a document, by tier."""
    sequences = pieces.groupBy("sequence_id", "tier").agg(F.sum("length").alias("used"), F.count("*").alias("pieces"))
    return sequences.groupBy("tier").agg(F.count("*").alias("sequences"), F.sum("used").alias("tokens"), F.sum(F.col("tier") - F.col("used")).alias("padded"), F.sum("pieces").alias("pieces"))
