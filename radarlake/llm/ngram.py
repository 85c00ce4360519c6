"""Interpolated modified Kneser-Ney trigrams, counted in Spark, kept as sorted hash arrays that workers map.

Fitting takes a few exchanges of packed counts. Word hashes go to ranges of the hash space
and give each word its number, its rank among all hashes. Triples of numbers go to buckets
by a hash of their last two words, so that a frequent word is spread and a bucket knows of
each pair how often it came and how many words came before it. What the buckets know of
each context (a word, by numbers of pairs) and of each follower goes to ranges of numbers,
and what they know of contexts of two words with triples seen twice and more to the bucket
of that pair; triples seen once follow from the pair's own count. Each step writes sorted
arrays to the shared folder; the driver keeps sizes and counts of counts alone.

Scoring maps those arrays. P(w | u v) = (c(uvw) - D(c(uvw))) / c(uv) + g(uv) P(w | v),
where P(w | v) does the same with numbers of words before a pair in place of counts (a pair
that opens a text keeps its count), over P(w) by numbers of contexts, over a uniform share
for all words and one unknown word; D are the three modified discounts of each level. No
count is cut off. Pairs and triples are told apart by 40 bits of a hash within a bucket.

Words are lower-cased (A-Z) and end at ASCII white space; each text, null and empty ones
too, ends with one end token. Repeated rows count as often as they come, null ids as any
other. Without training texts every word is unknown.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from radarlake.llm.common import chunks, mix, partitions, release, scratch, stored, tidy, word_hashes
from radarlake.llm.packed import map_bundle, map_file, merge, pack, planes, put_bundle, put_file, range_bucket, search, unpack, unplanes, values

#: The hash of the end token; words hash to it no more often than to each other.
END = np.uint64(0x5DEECE66D1234567)
#: Distinct keys that a task gathers before it sends them.
HELD = 1 << 20
#: Tokens whose triples a task gathers before it sends them.
HELD_TRIPLES = 1 << 19


def tokens(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of each row with the end token after them, and where the rows start."""
    hashed, before = word_hashes(data, offsets)
    first = before + np.arange(len(before))
    out = np.full(int(first[-1]), END, np.uint64)
    keep = np.ones(len(out), bool)
    keep[first[1:] - 1] = False
    out[keep] = hashed
    return out, first


def _by_bucket(bucket: np.ndarray, keys: np.ndarray, counts: np.ndarray) -> pa.RecordBatch:
    """A row per bucket of sorted keys and their counts."""
    order = np.argsort(bucket, kind="stable")
    b, k, c = bucket[order], keys[order], counts[order]
    edge = np.flatnonzero(np.concatenate([[True], b[1:] != b[:-1]])) if len(b) else np.zeros(0, np.int64)
    ends = np.append(edge[1:], len(b))
    return pa.RecordBatch.from_arrays(
        [pa.array(b[edge], pa.int32()), pa.array([pack(k[x:y]) for x, y in zip(edge, ends, strict=True)], pa.binary()), pa.array([planes(c[x:y]) for x, y in zip(edge, ends, strict=True)], pa.binary())],
        names=["bucket", "keys", "counts"],
    )


_PACKED = "bucket int, keys binary, counts binary"


def _gather(count, bucket):
    """Sums `count(data, offsets)` -> (keys, counts) over a task and sends them by `bucket(keys)`."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, counts, held = [], [], 0
        for _, data, offsets in chunks(batches, "text", 1 << 20):
            k, c = count(data, offsets)
            keys.append(k)
            counts.append(c)
            held += len(k)
            if held > HELD:
                k, c = merge(keys, counts)
                if len(k) > HELD // 2:
                    yield _by_bucket(bucket(k), k, c)
                    keys, counts, held = [], [], 0
                else:
                    keys, counts, held = [k], [c], len(k)
        k, c = merge(keys, counts)
        if len(k):
            yield _by_bucket(bucket(k), k, c)

    return run


def _reduce(finish):
    """Calls `finish(bucket, keys, counts)` for each bucket of a task, whose rows stand together."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, keys, counts = None, [], []
        for batch in batches:
            for b, k, c in values(batch, "bucket", "keys", "counts"):
                if b != here:
                    if here is not None:
                        yield finish(here, *merge(keys, counts))
                    here, keys, counts = b, [], []
                keys.append(unpack(k))
                counts.append(unplanes(c))
        if here is not None:
            yield finish(here, *merge(keys, counts))

    return run


def _dealt(df: DataFrame) -> DataFrame:
    return df.repartition(partitions(df.sparkSession), "bucket").sortWithinPartitions("bucket")


class Words:
    """The mapped word arrays: numbers and counts of hashes."""

    def __init__(self, path: str, first: list[int]):
        self.path, self.buckets, self.first = path, len(first) - 1, first

    def number(self, hashed: np.ndarray) -> np.ndarray:
        """Numbers of sorted distinct hashes, -1 for unknown words."""
        out = np.full(len(hashed), -1, np.int64)
        edges = np.searchsorted(range_bucket(hashed, self.buckets), np.arange(self.buckets + 1))
        for b in np.flatnonzero(np.diff(edges)).tolist():
            if self.first[b + 1] > self.first[b]:
                at = search(map_file(f"{self.path}/words-{b}", "<u8"), hashed[edges[b] : edges[b + 1]])
                out[edges[b] : edges[b + 1]] = np.where(at < 0, -1, at + self.first[b])
        return out

    def count(self, number: np.ndarray) -> np.ndarray:
        return _dense(self.path, "word-counts", self.first, number, 1)[:, 0]


def _dense(path: str, name: str, first: list[int], number: np.ndarray, width: int) -> np.ndarray:
    """Rows of dense arrays stored by ranges of numbers; zeros for -1."""
    out = np.zeros((len(number), width), np.int64)
    part = np.searchsorted(first[:-1], number, "right") - 1
    part[number < 0] = -1
    for b in np.unique(part[part >= 0]).tolist():
        here = np.flatnonzero(part == b)
        out[here] = map_file(f"{path}/{name}-{b}", "<i8").reshape(-1, width)[number[here] - first[b]]
    return out


def _word_counts(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return np.unique(tokens(data, offsets)[0], return_counts=True)


def _triples(words: Words, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Numbers of the second last word, the last word and the word at each token, and where rows start.

    The start of a text has the number after the last word's; before the first token there is one more, for nothing.
    """
    hashed, first = tokens(data, offsets)
    distinct, where = np.unique(hashed, return_inverse=True)
    number = words.number(distinct)[where]
    size = words.first[-1]
    last = np.concatenate([[0], number[:-1]])
    last[first[:-1]] = size
    second = np.concatenate([[0], last[:-1]])
    second[first[:-1]] = size + 1
    return second, last, number, first


def _key(context: np.ndarray, number: np.ndarray, size: int) -> np.ndarray:
    return context.astype(np.uint64) * np.uint64(size + 2) + number.astype(np.uint64)


def _pair_bucket(keys: np.ndarray, buckets: int) -> np.ndarray:
    return (mix(keys + np.uint64(1)) % np.uint64(buckets)).astype(np.int64)


def _hash40(pair: np.ndarray, before: np.ndarray | int = -1) -> np.ndarray:
    """40 bits for a pair, or for a pair and the word before it."""
    return mix(pair * np.uint64(0xD6E8FEB86659FD93) + np.asarray(before, np.int64).astype(np.uint64)) >> np.uint64(24)


def _keys(hashed: np.ndarray) -> dict[str, np.ndarray]:
    """Sorted 40-bit keys: their upper bits and their lower ones."""
    return {"high": (hashed >> np.uint64(8)).astype("<u4"), "low": (hashed & np.uint64(255)).astype(np.uint8)}


def _find(table: dict[str, np.ndarray], hashed: np.ndarray) -> np.ndarray:
    """Places of keys, -1 for those that aren't there."""
    at = np.full(len(hashed), -1, np.int64)
    if not table:
        return at
    high, low = table["high"], table["low"]
    h, rest = (hashed >> np.uint64(8)).astype(np.uint32), (hashed & np.uint64(255)).astype(np.uint8)
    spot = np.searchsorted(high, h)
    # equal upper bits stand together; their lower ones rise
    open_ = np.flatnonzero(spot < len(high))
    while len(open_):
        open_ = open_[high[spot[open_]] == h[open_]]
        hit = low[spot[open_]] == rest[open_]
        at[open_[hit]] = spot[open_[hit]]
        open_ = open_[~hit]
        spot[open_] += 1
        open_ = open_[spot[open_] < len(high)]
    return at


def _counts(name: str, counts: np.ndarray) -> dict[str, np.ndarray]:
    """Counts as bytes, and places and values of those from 255 on."""
    large = np.flatnonzero(counts >= 255)
    return {name: np.minimum(counts, 255).astype(np.uint8), f"{name}_place": large.astype("<i8"), f"{name}_value": counts[large].astype("<i8")}


def _get_counts(table: dict[str, np.ndarray], name: str, at: np.ndarray) -> np.ndarray:
    found = table[name][at].astype(np.int64)
    if len(table[f"{name}_place"]):
        big = np.flatnonzero(found == 255)
        found[big] = table[f"{name}_value"][np.searchsorted(table[f"{name}_place"], at[big])]
    return found


def _few(counts: np.ndarray) -> dict[str, np.ndarray]:
    """Counts that mostly are one: places and values of the others."""
    some = np.flatnonzero(counts != 1)
    return {"at": some.astype("<u4"), **_counts("n", counts[some])}


def _get_few(table: dict[str, np.ndarray], at: np.ndarray) -> np.ndarray:
    out = np.ones(len(at), np.int64)
    if len(some := table["at"]):
        spot = np.minimum(np.searchsorted(some, at.astype(np.uint32)), len(some) - 1)
        hit = np.flatnonzero(some[spot] == at)
        out[hit] = _get_counts(table, "n", spot[hit])
    return out


def _summed(pair: np.ndarray, before: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct triples with summed counts, of triples in the order of pair and word before."""
    first = np.flatnonzero(np.concatenate([[True], (pair[1:] != pair[:-1]) | (before[1:] != before[:-1])])) if len(pair) else np.zeros(0, np.int64)
    return pair[first], before[first], np.add.reduceat(count, first, dtype=np.int64) if len(first) else count


def _gather_triples(words: Words, buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pairs, befores, held = [], [], 0
        size = words.first[-1]

        def flush() -> pa.RecordBatch:
            pair, before = np.concatenate(pairs), np.concatenate(befores)
            pairs.clear()
            befores.clear()
            order = np.lexsort((before, pair))
            pair, before, count = _summed(pair[order], before[order], np.ones(len(pair), np.int32))
            b = _pair_bucket(pair, buckets)
            order = np.argsort(b, kind="stable")
            b, pair, before, count = b[order], pair[order], before[order], count[order]
            edge = np.flatnonzero(np.concatenate([[True], b[1:] != b[:-1]]))
            cuts = list(zip(edge.tolist(), [*edge[1:].tolist(), len(b)], strict=True))
            return pa.RecordBatch.from_arrays(
                [pa.array(b[edge], pa.int32()), pa.array([pack(pair[x:y]) for x, y in cuts], pa.binary()), pa.array([planes(np.concatenate([before[x:y], count[x:y]])) for x, y in cuts], pa.binary())],
                names=["bucket", "keys", "counts"],
            )

        for _, data, offsets in chunks(batches, "text", 1 << 20):
            second, last, number, _ = _triples(words, data, offsets)
            pairs.append(_key(last, number, size))
            befores.append(second)
            held += len(second)
            if held > HELD_TRIPLES:
                yield flush()
                held = 0
        if held:
            yield flush()

    return run


class Model:
    """What scoring needs: where the arrays lie, their sizes, and the discounts of the three levels."""

    def __init__(self, path: str, buckets: int, first: list[int], ranges: list[int], total: int, triple_discounts: list[float], pair_discounts: list[float], word_discounts: list[float], followers: list[int]):
        self.path, self.buckets, self.first, self.ranges, self.total = path, buckets, first, ranges, total
        self.triple_discounts, self.pair_discounts, self.word_discounts = triple_discounts, pair_discounts, word_discounts
        #: Distinct pairs, and words that follow one, two, more contexts.
        self.followers = followers

    @property
    def size(self) -> int:
        return self.first[-1]


def discounts(counts: list[int]) -> list[float]:
    """Modified Kneser-Ney discounts for one, two, three and more from the numbers of keys seen one to four times."""
    n1, n2, n3, n4 = counts
    if not n1 or not n2:
        return [0.0, 0.5, 0.5, 0.5]
    y = n1 / (n1 + 2 * n2)
    d = [1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3 if n3 else 0.5]
    return [0.0, *(min(max(x, 1e-3), k + 1 - 1e-3) for k, x in enumerate(d))]


def _write_words(path: str):
    def finish(bucket: int, keys: np.ndarray, counts: np.ndarray) -> pa.RecordBatch:
        put_file(f"{path}/words-{bucket}", keys.astype("<u8"))
        put_file(f"{path}/word-counts-{bucket}", counts.astype("<i8"))
        return pa.RecordBatch.from_arrays([pa.array([bucket], pa.int32()), pa.array([len(keys)], pa.int64()), pa.array([int(counts.sum())], pa.int64())], names=["bucket", "n", "total"])

    return finish


#: Buckets of pairs whose contexts of two words go together.
TOGETHER = 4
#: What a bucket of triples tells: sums for a range of words, for contexts of two words, and counts of counts.
_WORDS, _CONTEXTS, _TOTALS = 0, 1, 2
_SUMS = "kind int, bucket int, keys binary, counts binary"


def _write_triples(path: str, ranges: list[int], buckets: int):
    """Stores a bucket's pairs and triples, and tells contexts and followers what it knows of them."""
    size = ranges[-1]

    def finish(bucket: int, pair: np.ndarray, before: np.ndarray, count: np.ndarray) -> pa.RecordBatch:
        pair, before, count = _summed(pair, before, count)
        first = np.flatnonzero(np.concatenate([[True], pair[1:] != pair[:-1]]))
        keys, raw = pair[first], np.add.reduceat(count, first)
        last = (keys // np.uint64(size + 2)).astype(np.int64)
        # words before a pair; a pair that opens a text has none and keeps its count
        left = np.where(last == size, raw, np.diff(np.append(first, len(pair))))
        hashed = _hash40(keys)
        order = np.argsort(hashed)
        put_bundle(f"{path}/pairs-{bucket}", **_keys(hashed[order]), **_counts("raw", raw[order]), **_counts("left", left[order]))
        whole = before <= size
        hashed = _hash40(pair[whole], before[whole])
        order = np.argsort(hashed)
        put_bundle(f"{path}/triples-{bucket}", **_keys(hashed[order]), **_few(count[whole][order]))
        del hashed, order
        rows = []

        def tell(kind: int, part: np.ndarray, ids: np.ndarray, sums: list[np.ndarray]) -> None:
            edge = np.flatnonzero(np.concatenate([[True], part[1:] != part[:-1]])) if len(part) else np.zeros(0, np.int64)
            for x, y in zip(edge.tolist(), np.append(edge[1:], len(part)).tolist(), strict=False):
                rows.append((kind, int(part[x]), pack(ids[x:y]), planes(np.concatenate([s[x:y] for s in sums]))))

        # pairs stand by context
        own = np.flatnonzero(np.concatenate([[True], last[1:] != last[:-1]]))
        in_range = lambda ids: np.searchsorted(ranges[:-1], ids, "right") - 1
        tell(_WORDS, in_range(last[own]), last[own], [np.add.reduceat(x, own, dtype=np.int64) for x in (left, left == 1, left == 2, left > 2)])
        ids, n = np.unique((keys % np.uint64(size + 2)).astype(np.int64), return_counts=True)
        tell(_WORDS, in_range(ids), ids, [n])
        # contexts of two words, for triples seen twice and more
        some = np.flatnonzero(whole & (count > 1))
        context = _key(before[some], (pair[some] // np.uint64(size + 2)).astype(np.int64), size)
        part = _pair_bucket(context, buckets) // TOGETHER
        order = np.lexsort((context, part))
        context, part, c = context[order], part[order], count[some][order]
        own = np.flatnonzero(np.concatenate([[True], context[1:] != context[:-1]])) if len(c) else np.zeros(0, np.int64)
        if len(own):
            tell(_CONTEXTS, part[own], context[own], [np.add.reduceat(x, own, dtype=np.int64) for x in (c, c == 2, c > 2)])
        of = lambda x: [int((x == k).sum()) for k in range(1, 5)]
        rows.append((_TOTALS, 0, pack(keys[:0]), planes(np.array([*of(count[whole]), *of(left)]))))
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int32(), pa.binary(), pa.binary()), strict=True)], names=["kind", "bucket", "keys", "counts"])

    return finish


def _reduce_triples(finish):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, parts = None, []

        def closed() -> pa.RecordBatch:
            columns = [np.concatenate(x) for x in zip(*parts, strict=True)]
            parts.clear()
            order = np.lexsort((columns[1], columns[0]))
            columns = [c[order] for c in columns]
            del order
            return finish(here, *columns)

        for batch in batches:
            for b, k, c in values(batch, "bucket", "keys", "counts"):
                if b != here:
                    if parts:
                        yield closed()
                    here = b
                both = unplanes(c)
                parts.append((unpack(k), both[: len(both) // 2].astype(np.uint32), both[len(both) // 2 :].astype(np.int32)))
        if parts:
            yield closed()
        tidy()

    return run


def _write_two(path: str, buckets: int):
    """Sums of contexts of two words, by the bucket of the pair; what comes holds a few buckets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, keys, sums = None, [], []

        def close() -> pa.RecordBatch:
            k, s = merge(keys, sums)
            hashed, part = _hash40(k), _pair_bucket(k, buckets)
            for b in np.unique(part).tolist():
                mine = np.flatnonzero(part == b)
                mine = mine[np.argsort(hashed[mine])]
                columns = dict(x for j in range(3) for x in _counts(f"s{j}", s[mine, j]).items())
                put_bundle(f"{path}/two-{b}", **_keys(hashed[mine]), **columns)
            return pa.RecordBatch.from_arrays([pa.array([len(k)], pa.int64())], names=["n"])

        for batch in batches:
            for b, k, c in values(batch, "bucket", "keys", "counts"):
                if b != here:
                    if keys:
                        yield close()
                    here, keys, sums = b, [], []
                keys.append(unpack(k))
                sums.append(unplanes(c).reshape(3, -1).T)
        if keys:
            yield close()
        tidy()

    return run


def _write_contexts(path: str, ranges: list[int]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, sums = None, None

        def close() -> pa.RecordBatch:
            put_file(f"{path}/contexts-{here}", sums.astype("<i8"))
            n = sums[:, 4]
            return pa.RecordBatch.from_arrays([pa.array([int((n == k).sum()) for k in range(1, 5)], pa.int64()), pa.array([int(n.sum()), int((n > 2).sum()), 0, 0], pa.int64()), pa.array([0, 1, 2, 3], pa.int32())], names=["seen", "more", "k"])

        for batch in batches:
            for b, k, c in values(batch, "bucket", "keys", "counts"):
                if b != here:
                    if here is not None:
                        yield close()
                    # the start of a text has a place after the last word
                    here, sums = b, np.zeros((ranges[b + 1] - ranges[b] + (b == len(ranges) - 2), 5), np.int64)
                at, told = unpack(k).astype(np.int64) - ranges[b], unplanes(c)
                if len(told) == len(at):  # followers
                    sums[at, 4] += told
                else:
                    sums[at, :4] += told.reshape(4, -1).T
        if here is not None:
            yield close()

    return run


def fit(train: DataFrame, path: str | None = None) -> Model:
    """Counts the column `text` of all rows and leaves the model's arrays at `path` in the shared folder."""
    spark = train.sparkSession
    path = path or scratch(spark, "trigrams")
    # a task holds one bucket of triples at a time; words are fewer
    buckets, word_buckets = 2 * partitions(spark), max(1, partitions(spark) // 2)
    texts = train.select("text")
    sent = texts.mapInArrow(_gather(_word_counts, lambda k: range_bucket(k, word_buckets)), _PACKED)
    made = _dealt(sent).mapInArrow(_reduce(_write_words(path)), "bucket int, n long, total long").collect()  # a row a bucket
    sizes = {r["bucket"]: r["n"] for r in made}
    first = [0]
    for b in range(word_buckets):
        first.append(first[-1] + sizes.get(b, 0))
    if first[-1] >= (1 << 32) - 2:
        raise ValueError("pairs of word numbers need more than 64 bits")
    words = Words(path, first)
    # ranges of numbers without empty ones; the number after the last word's, the start of texts, is in the last
    ranges = sorted(set(first)) if first[-1] else [0, 0]
    sent = texts.mapInArrow(_gather_triples(words, buckets), _PACKED)
    told = stored(_dealt(sent).mapInArrow(_reduce_triples(_write_triples(path, ranges, buckets)), _SUMS), "trigram-sums")
    totals = np.sum([np.zeros(8, np.int64), *(unplanes(r["counts"]) for r in told.filter(F.col("kind") == _TOTALS).select("counts").collect())], axis=0)
    _dealt(told.filter(F.col("kind") == _CONTEXTS)).mapInArrow(_write_two(path, buckets), "n long").agg(F.sum("n")).collect()
    sums = _dealt(told.filter(F.col("kind") == _WORDS)).mapInArrow(_write_contexts(path, ranges), "seen long, more long, k int")
    seen = {r["k"]: (r["seen"], r["more"]) for r in sums.groupBy("k").agg(F.sum("seen").alias("seen"), F.sum("more").alias("more")).collect()}
    release(told)
    seen = {k: seen.get(k, (0, 0)) for k in range(4)}
    word_counts = [seen[k][0] for k in range(4)]
    return Model(path, buckets, first, ranges, sum(r["total"] for r in made), discounts([int(x) for x in totals[:4]]), discounts([int(x) for x in totals[4:]]), discounts(word_counts), [seen[0][1], word_counts[0], word_counts[1], seen[1][1]])


def _by_bucket_of(model: Model, pair: np.ndarray, hashed: np.ndarray):
    """(bucket, places) of the keys of each bucket, sorted by their hash."""
    bucket = _pair_bucket(pair, model.buckets)
    order = np.argsort(bucket.astype(np.uint64) << np.uint64(40) | hashed)
    edges = np.searchsorted(bucket[order], np.arange(model.buckets + 1))
    for b in np.flatnonzero(np.diff(edges)).tolist():
        yield b, order[edges[b] : edges[b + 1]]


def _pairs(model: Model, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of pairs in any order: how often they came, how many words came before, and sums (counts, twos, more) of their triples seen twice and more."""
    raw, left, sums = np.zeros(len(keys), np.int64), np.zeros(len(keys), np.int64), np.zeros((len(keys), 3), np.int64)
    hashed = _hash40(keys)
    for b, here in _by_bucket_of(model, keys, hashed):
        table = map_bundle(f"{model.path}/pairs-{b}")
        at = _find(table, hashed[here])
        here, at = here[at >= 0], at[at >= 0]
        if not len(at):
            continue
        raw[here], left[here] = _get_counts(table, "raw", at), _get_counts(table, "left", at)
        more = here[raw[here] > 1]
        table = map_bundle(f"{model.path}/two-{b}")
        at = _find(table, hashed[more])
        more, at = more[at >= 0], at[at >= 0]
        if len(at):
            for j in range(3):
                sums[more, j] = _get_counts(table, f"s{j}", at)
    return raw, left, sums


def _triple_counts(model: Model, pair: np.ndarray, before: np.ndarray) -> np.ndarray:
    """Counts of triples in any order, 0 for those unseen."""
    out = np.zeros(len(pair), np.int64)
    hashed = _hash40(pair, before)
    for b, here in _by_bucket_of(model, pair, hashed):
        table = map_bundle(f"{model.path}/triples-{b}")
        at = _find(table, hashed[here])
        here, at = here[at >= 0], at[at >= 0]
        if len(at):
            out[here] = _get_few(table, at)
    return out


def log10_words(model: Model, second: np.ndarray, last: np.ndarray, number: np.ndarray) -> np.ndarray:
    """log10 P(word | two words before it) for the numbers of `_triples`, tokens in their order; -1 is an unknown word."""
    if not model.size:
        return np.zeros(len(number))
    f, d, e = (np.array(x) for x in (model.triple_discounts, model.pair_discounts, model.word_discounts))
    ids, where = np.unique(np.concatenate([last, number]), return_inverse=True)
    known = _dense(model.path, "contexts", model.ranges, ids, 5)
    told, follows = known[where[: len(last)]], known[where[len(last) :], 4]
    pairs, one, two, more = model.followers
    share = float(e[1] * one + e[2] * two + e[3] * more) / pairs
    out = np.maximum(follows - e[np.minimum(follows, 3)], 0) / pairs + share / (model.size + 1)
    both = np.flatnonzero((last >= 0) & (number >= 0))
    key = _key(last[both], number[both], model.size)
    distinct, back = np.unique(key, return_inverse=True)
    raw, left, sums = np.zeros(len(number), np.int64), np.zeros(len(number), np.int64), np.zeros((len(number), 3), np.int64)
    raw[both], left[both], sums[both] = (x[back] for x in _pairs(model, distinct))
    has = np.flatnonzero(told[:, 0] > 0)
    total, n = told[has, 0], left[has]
    out[has] = np.maximum(n - d[np.minimum(n, 3)], 0) / total + (told[has, 1:4] * d[1:]).sum(1) / total * out[has]
    # the context of two words is the pair of the token before
    has = np.flatnonzero(second <= model.size)
    has = has[raw[has - 1] > 0]
    counts = np.zeros(len(number), np.int64)
    asked = has[(number[has] >= 0) & (left[has] > 0)]
    counts[asked] = _triple_counts(model, _key(last[asked], number[asked], model.size), second[asked])
    total, told = raw[has - 1], sums[has - 1]
    once = total - told[:, 0]
    kept = (f[1] * once + f[2] * told[:, 1] + f[3] * told[:, 2]) / total
    out[has] = np.maximum(counts[has] - f[np.minimum(counts[has], 3)], 0) / total + kept * out[has]
    return np.log10(out)


def _score(model: Model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = Words(model.path, model.first)
        n, v = model.total, model.size
        for rows, data, offsets in chunks(batches, "text", 1 << 20):
            second, last, number, first = _triples(words, data, offsets)
            ids, where = np.unique(number, return_inverse=True)
            count = words.count(ids)[where]
            total = lambda x: np.add.reduceat(x, first[:-1])  # noqa: E731, B023
            base = total(np.log10((count + 0.1) / (n + 0.1 * (v + 1))))
            score = total(log10_words(model, second, last, number))
            size = np.diff(first)
            get = lambda c: rows.column(rows.schema.get_field_index(c))  # noqa: E731, B023
            yield pa.RecordBatch.from_arrays(
                [get("doc_id"), get("held_out"), pa.array(size), pa.array(total((count > 0).astype(np.int64))), pa.array(np.full(len(size), n)), pa.array(base), pa.array(score), pa.array(10.0 ** (-score / size))],
                names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score", "perplexity"],
            )

    return run


def held_out(doc_id: Column) -> Column:
    """The tenth of the documents that nothing is learned from."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 10 == 0


def score(docs: DataFrame, model: Model) -> DataFrame:
    """Scores of all rows (doc_id, held_out, text) under a fitted model."""
    schema = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double, perplexity double"
    return docs.select("doc_id", "held_out", "text").mapInArrow(_score(model), schema)


def fit_and_score(docs: DataFrame) -> DataFrame:
    """Learns from the documents that aren't held out and scores all."""
    flagged = docs.select("doc_id", "text").withColumn("held_out", F.coalesce(held_out(F.col("doc_id")), F.lit(False)))
    return score(flagged, fit(flagged.filter("not held_out")))


def perplexity(scored: DataFrame) -> DataFrame:
    """Perplexity of the held-out and of the training part under the model and under the unigram base."""
    sums = scored.groupBy("held_out").agg(F.sum("score").alias("s"), F.sum("base_score").alias("b"), F.sum("n_tokens").alias("n"))
    ten = F.lit(10.0)
    return sums.select("held_out", F.pow(ten, -F.col("s") / F.col("n")).alias("perplexity"), F.pow(ten, -F.col("b") / F.col("n")).alias("base_perplexity"), (F.col("n") * math.log2(10)).alias("scale"))
