"""Benchmark passages in documents by spaced seeds.

A seed hashes the words of a window at the positions that a fixed mask keeps, so that a
replaced word at another position does not matter. Seeds of the test items meet the
seeds of all documents; around each meeting the item is laid over the document and
the equal words are counted, and a document holds an item if at least `overlap` of the
item's words agree at one place.

Items of up to SHORT words also get the masks of every so many positions, one more than
the words that `overlap` lets differ: however those lie, one of the masks misses them all, so
no short item is lost. Over longer ones the fixed masks are measured, not proved: the tests
draw patterns of replaced words and ask for 99.5 % of them.

The test items are the stated query set: they go to the workers in blocks of proven
size, one pass over the documents a block. Words are split at ASCII white space, lower-cased (A-Z).
Null or empty texts hold nothing, items without words or without an item_id are in no document, a
repeated item_id counts as one item for each of its rows, and of equal overlaps the first
place stands. Rows that repeat a doc_id and null ids are searched and removed row by row.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from radarlake.llm.common import HashIndex, chunks, mix, word_hashes

#: Fixed masks of five words each, laid at every place.
MASKS = ("11111", "1101011", "110010011", "1010100101001")
#: Words of an item up to which masks of every so many positions are laid, too.
SHORT = 14
OVERLAP = 0.8
#: Bytes of test texts that one pass sends to the workers.
BLOCK_BYTES = 16 << 20
SCHEMA = "doc_id long, item_id long, n_matched long, n_item long, place long, overlap double"


def seeds_of(n: int, overlap: float, masks: tuple[str, ...] = MASKS) -> list[tuple[tuple[int, ...], range]]:
    """For an item of n words: masks, as positions that count, and the places at which they are laid."""
    out = []
    for m in masks:
        mask = tuple(i for i, c in enumerate(m) if c == "1")
        if len(m) <= n:
            out.append((mask, range(n - mask[-1])))
    if n <= SHORT or not out:
        step = n - math.ceil(overlap * n - 1e-9) + 1
        out += [(tuple(range(0, n - r, step)), range(r, r + 1)) for r in range(min(step, n))]
    return out


def _seeds(hashed: np.ndarray, at: np.ndarray, mask: tuple[int, ...]) -> np.ndarray:
    out = np.full(len(at), np.uint64(sum(1 << i for i in mask) % (1 << 64)), np.uint64)
    for i in mask:
        out = mix(out * np.uint64(0xA0761D6478BD642F) + hashed[at + i])
    return out


class Items:
    """Words and seeds of a block of test items."""

    def __init__(self, ids: list[int], texts: list[str | None], overlap: float = OVERLAP, masks: tuple[str, ...] = MASKS):
        raw = [(t or "").encode() for t in texts]
        offsets = np.concatenate([[0], np.cumsum([len(x) for x in raw])]).astype(np.int64)
        self.ids = np.array(ids, np.int64)
        self.words, self.first = word_hashes(np.frombuffer(b"".join(raw), np.uint8), offsets)
        seeds, item, place = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        self.masks: list[tuple[int, ...]] = []
        for i, (a, b) in enumerate(zip(self.first[:-1].tolist(), self.first[1:].tolist(), strict=True)):
            for mask, places in seeds_of(b - a, overlap, masks) if b > a else []:
                if mask not in self.masks:
                    self.masks.append(mask)
                at = a + np.arange(places.start, places.stop)
                seeds.append(_seeds(self.words, at, mask))
                item.append(np.full(len(at), i))
                place.append(at - a)
        seeds = np.concatenate(seeds)
        order = np.argsort(seeds, kind="stable")
        distinct, start = np.unique(seeds[order], return_index=True)
        self.item, self.place = np.concatenate(item)[order], np.concatenate(place)[order]
        self.start = np.append(start, len(order))
        self.index = HashIndex(max(1, len(distinct)))
        self.index.add(distinct)

    def search(self, hashed: np.ndarray, first: np.ndarray, overlap: float) -> list[tuple[int, int, int, int, int]]:
        """(row, item, equal words, words of the item, place in the row), one for each row that holds an item."""
        found: dict[tuple[int, int], tuple[int, int]] = {}
        row_of = np.repeat(np.arange(len(first) - 1), np.diff(first))
        for mask in self.masks:
            at = np.arange(max(0, len(hashed) - mask[-1]))
            at = at[row_of[at] == row_of[at + mask[-1]]] if len(at) else at
            number = self.index.find(_seeds(hashed, at, mask))
            met = np.flatnonzero(number >= 0)
            for a in range(0, len(met), 4096):
                self._lay(hashed, first, row_of, at[met[a : a + 4096]], number[met[a : a + 4096]], overlap, found)
        return [(r, i, n, int(self.first[i + 1] - self.first[i]), place) for (r, i), (n, place) in found.items()]

    def _lay(self, hashed: np.ndarray, first: np.ndarray, row_of: np.ndarray, at: np.ndarray, number: np.ndarray, overlap: float, found: dict) -> None:
        times = self.start[number + 1] - self.start[number]
        which = np.repeat(self.start[number] - (np.cumsum(times) - times), times) + np.arange(times.sum())
        at = np.repeat(at, times)
        laid = np.unique(np.stack([row_of[at], self.item[which], at - self.place[which]], 1), axis=0)
        for b in range(0, len(laid), 8192):
            row, item, start = laid[b : b + 8192].T
            size = self.first[item + 1] - self.first[item]
            inner = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
            there = np.repeat(start, size) + inner
            inside = (there >= np.repeat(first[row], size)) & (there < np.repeat(first[row + 1], size))
            equal = inside & (hashed[np.clip(there, 0, len(hashed) - 1)] == self.words[np.repeat(self.first[item], size) + inner])
            n = np.add.reduceat(equal.astype(np.int64), np.cumsum(size) - size)
            for k in np.flatnonzero(n >= overlap * size - 1e-9).tolist():
                key, value = (int(row[k]), int(item[k])), (int(n[k]), int(start[k] - first[row[k]]))
                if key not in found or (-value[0], value[1]) < (-found[key][0], found[key][1]):
                    found[key] = value


def _search(shared, overlap: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items = Items(*shared.value, overlap)
        for rows, data, offsets in chunks(batches, "text"):
            hits = items.search(*word_hashes(data, offsets), overlap)
            if hits:
                r, i, n, size, at = (np.array(x) for x in zip(*hits, strict=True))
                doc = rows.column(rows.schema.get_field_index("doc_id")).take(pa.array(r))
                yield pa.RecordBatch.from_arrays([doc, pa.array(items.ids[i]), pa.array(n), pa.array(size), pa.array(at), pa.array(n / size)], names=["doc_id", "item_id", "n_matched", "n_item", "place", "overlap"])

    return run


def _holds(shared, overlap: float):
    def run(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        items = Items(*shared.value, overlap)
        for text in texts:
            out, done = np.zeros(len(text), bool), 0
            for rows, data, offsets in chunks(iter([pa.RecordBatch.from_arrays([text], names=["text"])]), "text"):
                for hit in items.search(*word_hashes(data, offsets), overlap):
                    out[done + hit[0]] = True
                done += rows.num_rows
            yield pa.array(out)

    return run


def _blocks(tests: DataFrame, block_bytes: int) -> list:
    """The test items, broadcast in blocks of about `block_bytes`."""
    spark = tests.sparkSession
    named_ = tests.filter("item_id is not null")
    size = named_.agg(F.coalesce(F.sum(F.octet_length("text") + 64), F.lit(0)).alias("n")).first()["n"]
    blocks = max(1, -(-int(size) // block_bytes))
    out = []
    for b in range(blocks):
        block = named_ if blocks == 1 else named_.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == b)
        rows = sorted(block.select("item_id", "text").collect(), key=lambda r: (r["item_id"], r["text"] or ""))
        out.append(spark.sparkContext.broadcast(([r["item_id"] for r in rows], [r["text"] for r in rows])))
    return out


def find(docs: DataFrame, tests: DataFrame, overlap: float = OVERLAP, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """A row for each document and test item (item_id, text) that it holds, with the best place."""
    kept = docs.select("doc_id", "text")
    return reduce(DataFrame.unionByName, (kept.mapInArrow(_search(shared, overlap), SCHEMA) for shared in _blocks(tests, block_bytes)))


def remove(docs: DataFrame, tests: DataFrame, overlap: float = OVERLAP, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The rows of `docs` that hold no test item, as they are; only texts go to Python, and nothing is exchanged."""
    out = docs
    for shared in _blocks(tests, block_bytes):
        out = out.filter(~F.arrow_udf(_holds(shared, overlap), "boolean")(F.col("text")))
    return out
