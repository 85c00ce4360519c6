"""Removal of byte strings that also start in an earlier document, by hash-compared suffix sorts.

Every string of `length` bytes holds an anchor: the smallest hash among its 18-byte
strings, leftmost of equals. The strings of a document that share an anchor form a
segment of neighbouring starts. Equal strings have equal anchors, so all that must meet
meets under an anchor:

1. Tasks send the anchors of their documents; those that several documents hold are candidates.
2. Documents send the bytes of their candidate segments. Equal segments keep the smallest
   id; segments with one anchor that differ are suffix-sorted, to the right from the
   anchor and, reversed, to the left: prefix polynomial hashes and binary search give
   common extensions, a mergesort compares by them, and neighbours are verified byte by
   byte. A string equals another where both extensions reach its ends, and each run of
   equal strings keeps its smallest id.
3. What was found goes back to the documents, which drop the covered bytes.

Tasks sum up before each exchange, so a bucket gets a key from a task once. Anchors that
a sample finds in more than a share of all documents are left out: each of their strings
goes by the hash of its own bytes, so that no bucket gathers the surroundings of a common
passage. Their number is bounded by that share and goes to all workers. Hashes only
propose: segments and strings that count as equal are compared by their bytes, in the
task that sends them and where they meet. Equal documents are found by digest first and
only the smallest id takes part.

Null texts count as empty; rows that repeat a doc_id are documents of their own, and
neither counts as earlier than the other; a row without a doc_id comes neither before nor
after another and loses nothing; texts shorter than `length` lose nothing.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from radarlake.llm.common import HashIndex, chunks, gather, mix, partitions, prefix_hashes, same_bytes, span_hashes, tidy
from radarlake.llm.common import _powers as powers
from radarlake.llm.packed import pack, planes, unpack, unplanes, values

LENGTH = 50
ANCHOR = 18
#: One document in so many is looked at for common anchors; in at least so many of them; the share of documents that makes an anchor common.
SAMPLE, COMMON_LEAST, COMMON_SHARE = 64, 16, 1e-4
#: Keys, or bytes of segments, that a task gathers before it sends them.
HELD, HELD_BYTES = 1 << 20, 1 << 23
#: Segments that one suffix sort holds, about; buckets of anchors and of segments for each partition.
SORTED, ANCHOR_BUCKETS, SEGMENT_BUCKETS = 1 << 15, 2, 4
#: Starts that one step looks at; a start's place in a step takes so many bits.
STEP, PLACE_BITS = 1 << 20, 21


class Segments:
    """Segments of a chunk by rising start: row, first and last start (both in), anchor's place in it, route and key.

    The route is the anchor's hash and the key that of the whole bytes. A string with an
    anchor in `common` is a segment of its own with place -1, and its key is its route.
    """

    def __init__(self, data: np.ndarray, offsets: np.ndarray, length: int = LENGTH, common: HashIndex | None = None):
        found = [self._step(data, offsets, length, common, a) for a in range(0, max(len(data) - length + 1, 0), STEP)]
        none = (np.zeros(0, np.int64),) * 4 + (np.zeros(0, np.uint64),) * 2
        self.row, self.lo, self.hi, self.place, self.route, self.key = (np.concatenate(x) for x in zip(none, *found, strict=True))

    @staticmethod
    def _step(data, offsets, length, common, a):
        b = min(a + STEP, len(data) - length + 1)
        first = int(np.searchsorted(offsets, a, "right")) - 1
        last = int(np.searchsorted(offsets, b, "left"))
        edge = np.clip(offsets[first : last + 1], a, None)
        span = np.diff(np.minimum(edge, b))
        row = np.repeat(np.arange(first, first + len(span)), span)
        starts = np.arange(b - a)
        whole = starts + a + length <= offsets[row + 1]
        starts, row = starts[whole], row[whole]
        if not len(starts):
            return (starts, starts, starts, starts, np.zeros(0, np.uint64), np.zeros(0, np.uint64))
        prefix = prefix_hashes(data[a : b + length - 1])
        n = len(prefix) - ANCHOR
        x = span_hashes(prefix, np.arange(n), np.arange(n) + ANCHOR)
        # the smallest hash, leftmost of equals, as one number: its upper bits and the place
        low = (x >> np.uint64(PLACE_BITS) << np.uint64(PLACE_BITS)) | np.arange(n, dtype=np.uint64)
        width, want = 1, length - ANCHOR + 1
        while width < want:
            step = min(width, want - width)
            low = np.minimum(low[:-step], low[step:])
            width += step
        at = (low[starts] & np.uint64((1 << PLACE_BITS) - 1)).astype(np.int64)
        begins = np.flatnonzero(np.concatenate([[True], (at[1:] != at[:-1]) | (row[1:] != row[:-1])]))
        row, place, lo, hi = row[begins], at[begins], starts[begins], starts[np.append(begins[1:], len(starts)) - 1]
        route = x[place]
        place = place - lo
        key = mix(span_hashes(prefix, lo, hi + length) + place.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        if common is not None and common.size and (hot := common.find(route) >= 0).any():
            n = (hi - lo + 1)[hot]
            each = np.repeat(lo[hot] - (np.cumsum(n) - n), n) + np.arange(n.sum())
            own = mix(span_hashes(prefix, each, each + length) ^ np.uint64(0x5851F42D4C957F2D))
            parts = ((row, np.repeat(row[hot], n)), (lo, each), (hi, each), (place, np.full(len(each), -1)), (route, own), (key, own))
            joined = [np.concatenate([old[~hot], new]) for old, new in parts]
            order = np.argsort(joined[1], kind="stable")
            row, lo, hi, place, route, key = (v[order] for v in joined)
        return row, lo + a, hi + a, place, route, key


def equal_groups(text: np.ndarray, at: np.ndarray, size: np.ndarray, keys: np.ndarray, docs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """An order by group and id, and where groups begin: equal keys whose bytes are equal, too."""
    order = np.lexsort((docs, keys))
    if not len(order):
        return order, np.zeros(0, bool)
    k = keys[order]
    first = np.concatenate([[True], k[1:] != k[:-1]])
    head = order[np.maximum.accumulate(np.where(first, np.arange(len(order)), 0))]
    fits = size[order] == size[head]
    fits[fits] = same_bytes(text, at[order[fits]], text, at[head[fits]], size[order[fits]])
    if not fits.all():
        # a hash lied: the bytes of the keys concerned decide
        odd = np.isin(keys, np.unique(keys[order[~fits]]))
        lied = np.flatnonzero(odd)
        number: dict[bytes, int] = {}
        sub = np.zeros(len(keys), np.int64)
        sub[lied] = [number.setdefault(text[at[i] : at[i] + size[i]].tobytes(), len(number)) for i in lied.tolist()]
        order = np.lexsort((docs, sub, keys))
        k, s = keys[order], sub[order]
        first = np.concatenate([[True], (k[1:] != k[:-1]) | (s[1:] != s[:-1])])
    return order, first


# --- the suffix sort --------------------------------------------------------------


def common_extension(prefix: np.ndarray, a: np.ndarray, b: np.ndarray, limit: np.ndarray) -> np.ndarray:
    """Lengths, up to each limit, for which the bytes from a and from b agree, by binary search on prefix hashes."""
    power, _ = powers(len(prefix))
    out = np.zeros(len(a), np.int64)
    if not len(a):
        return out
    pa_, pb, wa, wb = prefix[a], prefix[b], power[a], power[b]
    step = 1 << (int(limit.max()).bit_length() - 1) if limit.max() else 0
    while step:
        more = out + step
        can = np.flatnonzero(more <= limit)
        m = more[can]
        same = (prefix[a[can] + m] - pa_[can]) * wb[can] == (prefix[b[can] + m] - pb[can]) * wa[can]
        out[can[same]] += step
        step >>= 1
    return out


def sort_suffixes(text: np.ndarray, starts: np.ndarray, size: np.ndarray, group: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order of the strings text[start : start + size] within each group, and the bytes each shares with the one before it (0 for the first of a group).

    `group` rises; a string that begins another goes before it. A mergesort over all
    groups at once: a round merges neighbouring runs by ranking each string in the other
    run, and comparisons take common extensions. What neighbours share is verified on
    their bytes; if a hash lied, bytes decide order and extensions.
    """
    n = len(starts)
    order, share = np.arange(n), np.zeros(n, np.int64)
    if not n:
        return order, share
    prefix = prefix_hashes(text)
    first = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
    many = np.diff(np.append(first, n))
    base, members = np.repeat(first, many), np.repeat(many, many)
    local = np.arange(n) - base
    width = 1
    while width < many.max():
        live = np.flatnonzero(members > width)
        where, its, most = local[live], base[live], members[live]
        run = where // width
        other = run ^ 1
        lo, hi = np.minimum(other * width, most), np.minimum((other + 1) * width, most)
        left = (run & 1) == 0
        a, b = lo.copy(), hi.copy()
        open_ = np.flatnonzero(a < b)
        while len(open_):
            mid = (a[open_] + b[open_]) >> 1
            mine, its_ = order[live[open_]], order[its[open_] + mid]
            x, y = starts[mine], starts[its_]
            least = np.minimum(size[mine], size[its_])
            same = common_extension(prefix, x, y, least)
            whole = same >= least
            at = np.where(whole, 0, same)
            # a string of the left run goes before its equals of the right one
            by_size = np.where(left[open_], size[its_] < size[mine], size[its_] <= size[mine])
            before = np.where(whole, by_size, text[np.minimum(y + at, len(text) - 1)] < text[np.minimum(x + at, len(text) - 1)])
            a[open_[before]] = mid[before] + 1
            b[open_[~before]] = mid[~before]
            open_ = open_[a[open_] < b[open_]]
        to = its + np.minimum(run, other) * width + (where - run * width) + (a - lo)
        moved = order.copy()
        moved[to] = order[live]
        order = moved
        width *= 2
    near = np.flatnonzero(local > 0)
    x, y = starts[order[near]], starts[order[near - 1]]
    least = np.minimum(size[order[near]], size[order[near - 1]])
    share[near] = common_extension(prefix, x, y, least)
    some = near[share[near] > 0]
    if not same_bytes(text, starts[order[some]], text, starts[order[some - 1]], share[some]).all() or not _rising(text, starts, size, order, near, share):
        raw = [text[s : s + k].tobytes() for s, k in zip(starts.tolist(), size.tolist(), strict=True)]
        order = np.array(sorted(range(n), key=lambda i: (group[i], raw[i])), np.int64)
        for i in near.tolist():
            one, two = raw[order[i]], raw[order[i - 1]]
            share[i] = next((k for k, (p, q) in enumerate(zip(one, two, strict=False)) if p != q), min(len(one), len(two)))
    return order, share


def _rising(text, starts, size, order, near, share) -> bool:
    """Whether each string is at least the one before it, given the bytes they share."""
    one, two, k = order[near], order[near - 1], share[near]
    inside = (k < size[one]) & (k < size[two])
    up = text[(starts[one] + k)[inside]] > text[(starts[two] + k)[inside]]
    return bool(up.all() and (size[two][~inside] <= size[one][~inside]).all())


# --- step 1: anchors that several documents hold ----------------------------------

_SENT = "bucket int, kind int, keys binary, docs binary"
_TOLD = "doc_id long, key long"


def _split(bucket: np.ndarray) -> list[tuple[int, slice]]:
    if not len(bucket):
        return []
    edge = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]]))
    return [(int(bucket[x]), slice(int(x), int(y))) for x, y in zip(edge, np.append(edge[1:], len(bucket)), strict=True)]


def _flat(docs: np.ndarray, **columns: np.ndarray) -> pa.RecordBatch:
    """A row for each id and value; lists by bucket would be as many rows as a document has buckets, which grow with the table."""
    return pa.RecordBatch.from_arrays([pa.array(docs), *(pa.array(v.view(np.int64)) for v in columns.values())], names=["doc_id", *columns])


def _send_anchors(buckets: int, length: int, shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, docs, held = [], [], 0

        def flush() -> pa.RecordBatch:
            k, d = np.concatenate(keys), np.concatenate(docs)
            order = np.lexsort((d, k))
            k, d = k[order], d[order]
            new = np.concatenate([[True], (k[1:] != k[:-1]) | (d[1:] != d[:-1])])
            k, d = k[new], d[new]
            first = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
            times = np.diff(np.append(first, len(k)))
            rows = []
            # a key goes to its bucket once, with the smallest id: 0 of one document here, 1 of several; 2 tells all of those
            for kind, chosen in enumerate((first[times == 1], first[times > 1], np.flatnonzero(np.repeat(times > 1, times)))):
                b = ((k[chosen] >> np.uint64(40)).astype(np.int64) if kind < 2 else np.abs(d[chosen])) % buckets
                by = np.argsort(b, kind="stable")
                rows += [(bucket, kind, pack(k[chosen[by[s]]]), planes(d[chosen[by[s]]])) for bucket, s in _split(b[by])]
            keys.clear()
            docs.clear()
            return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int32(), pa.binary(), pa.binary()), strict=True)], names=["bucket", "kind", "keys", "docs"])

        for rows, data, offsets in chunks(batches, "text", 1 << 20):
            found = Segments(data, offsets, length, shared.value)
            ids = rows.column(rows.schema.get_field_index("doc_id"))
            has = ids.is_valid().to_numpy(zero_copy_only=False)[found.row]
            if not has.any():
                continue
            keys.append(found.route[has])
            docs.append(ids.fill_null(0).to_numpy()[found.row[has]])
            held += len(keys[-1])
            if held > HELD:
                yield flush()
                held = 0
        if held:
            yield flush()

    return run


def _meet_anchors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    keys, docs, asks, here = [], [], [], None

    def meet() -> pa.RecordBatch | None:
        if not keys:
            return None
        k, d, ask = np.concatenate(keys), np.concatenate(docs), np.concatenate(asks)
        order = np.argsort(k, kind="stable")
        k, d, ask = k[order], d[order], ask[order]
        same = np.zeros(len(k), bool)
        same[1:] = k[1:] == k[:-1]
        same[:-1] |= same[1:]
        tell = same & ask
        return _flat(d[tell], key=k[tell]) if tell.any() else None

    for batch in batches:
        for b, kind, k, d in values(batch, "bucket", "kind", "keys", "docs"):
            if b != here:
                if (made := meet()) is not None:
                    yield made
                here, keys, docs, asks = b, [], [], []
            if kind == 2:
                yield _flat(unplanes(d), key=unpack(k))
            else:
                keys.append(unpack(k))
                docs.append(unplanes(d))
                asks.append(np.full(len(keys[-1]), kind == 0))
    if (made := meet()) is not None:
        yield made
    tidy()


# --- step 2: segments under shared anchors ----------------------------------------

_SEGMENT = "bucket int, kind int, text binary, sizes binary, places binary, docs binary"


def _told(column: pa.Array, *fields: str) -> tuple[np.ndarray, list[np.ndarray]]:
    """The row of each told value and the values, of a column of lists (of structs)."""
    many = column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
    parts = column.flatten()
    return np.repeat(np.arange(len(many)), many), [x.to_numpy(zero_copy_only=False) for x in ([parts.field(f) for f in fields] or [parts])]


def _pairs(row: np.ndarray, key: np.ndarray) -> np.ndarray:
    return mix(key ^ mix(row.astype(np.uint64) + np.uint64(1)))


def _send_segments(buckets: int, length: int, shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        texts, fields, size = [], [], 0

        def flush() -> pa.RecordBatch:
            """A segment goes once, with its smallest id (kind 0); the other ids that hold it are known (kind 1)."""
            text = np.concatenate(texts)
            n, place, route, key, doc = (np.concatenate(x) for x in zip(*fields, strict=True))
            at = np.cumsum(n) - n
            order, first = equal_groups(text, at, n, key, doc)
            heads = order[first]
            lowest = doc[order[np.maximum.accumulate(np.where(first, np.arange(len(order)), 0))]]
            later = order[doc[order] > lowest]
            b = (route[heads] % np.uint64(buckets)).astype(np.int64)
            by = np.argsort(b, kind="stable")
            rows = []
            for bucket, s in _split(b[by]):
                x = heads[by[s]]
                rows.append((bucket, 0, text[gather(at[x], n[x])].tobytes(), planes(n[x]), planes(place[x]), planes(doc[x])))
            if len(later):
                x = later[np.lexsort((doc[later], key[later]))]
                rows.append((int(key[x[0]] % np.uint64(buckets)), 1, pack(key[x]), b"", b"", planes(doc[x])))
            texts.clear()
            fields.clear()
            return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int32(), *[pa.binary()] * 4), strict=True)], names=["bucket", "kind", "text", "sizes", "places", "docs"])

        for rows, data, offsets in chunks(batches, "text", 1 << 20):
            row, (told,) = _told(rows.column(rows.schema.get_field_index("told")))
            if not len(row):
                continue
            found = Segments(data, offsets, length, shared.value)
            ids = rows.column(rows.schema.get_field_index("doc_id")).to_numpy(zero_copy_only=False)
            asked = np.flatnonzero(np.isin(_pairs(found.row, found.route), _pairs(row, told.view(np.uint64))))
            if not len(asked):
                continue
            # a document sends equal segments once
            asked = asked[np.sort(np.unique(_pairs(found.row[asked], found.key[asked]), return_index=True)[1])]
            n = found.hi[asked] - found.lo[asked] + length
            texts.append(data[gather(found.lo[asked], n)])
            fields.append((n, found.place[asked], found.route[asked], found.key[asked], ids[found.row[asked]]))
            size += int(n.sum()) + 40 * len(n)
            if size > HELD_BYTES:
                yield flush()
                size = 0
        if size:
            yield flush()

    return run


_MARKS = "doc_id long, key long, mark long"
_ALL = -1


def _hashes(text: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """`span_hashes` of short spans with rising starts, a step of the text at a time."""
    out = np.zeros(len(start), np.uint64)
    step = start // STEP
    for a in np.flatnonzero(np.concatenate([[True], step[1:] != step[:-1]])).tolist() if len(start) else []:
        b = int(np.searchsorted(step, step[a], "right"))
        low, high = int(start[a]), int(end[a:b].max())
        out[a:b] = span_hashes(prefix_hashes(text[low:high]), start[a:b] - low, end[a:b] - low)
    return out


def meet_segments(text: np.ndarray, size: np.ndarray, place: np.ndarray, docs: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Keys, ids and marks (a bit per start, or all) of segments whose strings a smaller id holds too."""
    at = np.cumsum(size) - size
    single = place < 0
    whole = _hashes(text, at, at + size)
    keys = np.where(single, mix(whole ^ np.uint64(0x5851F42D4C957F2D)), mix(whole + np.maximum(place, 0).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)))
    order, first = equal_groups(text, at, size, keys, docs)
    lowest = docs[order[np.maximum.accumulate(np.where(first, np.arange(len(order)), 0))]]
    later = order[docs[order] > lowest]
    out = [(keys[later], docs[later], np.full(len(later), _ALL, np.int64))]
    # one of each distinct segment; anchors with several of them are sorted
    one = order[first]
    one = one[~single[one]]
    begin = at[one] + place[one]
    # `one` stands by key: its bytes are hashed in the order of their places
    by = np.argsort(begin)
    one, begin = one[by], begin[by]
    anchor = _hashes(text, begin, begin + ANCHOR)
    by = np.argsort(anchor, kind="stable")
    one, anchor = one[by], anchor[by]
    same = np.zeros(len(one), bool)
    same[1:] = anchor[1:] == anchor[:-1]
    same[:-1] |= same[1:]
    one, anchor = one[same], anchor[same]
    if not len(one):
        return tuple(np.concatenate(x) for x in zip(*out, strict=True))
    # whole anchors in turn, so that a sort holds about SORTED segments, or one anchor's
    first = np.flatnonzero(np.concatenate([[True], anchor[1:] != anchor[:-1]]))
    turn = first // SORTED
    cuts = [*first[np.flatnonzero(np.concatenate([[True], turn[1:] != turn[:-1]]))].tolist(), len(one)]
    for x, y in zip(cuts[:-1], cuts[1:], strict=True):
        mine = one[x:y]
        n = size[mine]
        packed = text[gather(at[mine], n)]
        group = np.cumsum(np.concatenate([[0], anchor[x + 1 : y] != anchor[x : y - 1]]))
        marks = mark_repeats(packed, n, place[mine], docs[mine], group, length)
        some = np.flatnonzero(marks)
        out.append((keys[mine[some]], docs[mine[some]], marks[some]))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def mark_repeats(text: np.ndarray, size: np.ndarray, place: np.ndarray, docs: np.ndarray, group: np.ndarray, length: int) -> np.ndarray:
    """For segments by rising group, the starts (as bits) of the strings that a segment of the group with a smaller id holds at the same distance from the anchor."""
    at = np.cumsum(size) - size
    total = len(text)
    right, shares = sort_suffixes(text, at + place, size - place, group)
    # the bytes before the anchor, read backwards
    left, before = sort_suffixes(text[::-1], total - at - place, place, group)
    n = len(size)
    marks = np.zeros(n, np.int64)
    new = np.concatenate([[True], group[1:] != group[:-1]])
    for j in range(length - ANCHOR + 1):
        # strings that begin j bytes before the anchor
        has = (place >= j) & (size - place >= length - j)
        if not has.any():
            continue
        one, two = np.empty(n, np.int64), np.empty(n, np.int64)
        one[right] = np.cumsum(new | (shares < length - j))
        two[left] = np.cumsum(new | (before < j))
        which = np.flatnonzero(has)
        pair = one[which] * (n + 1) + two[which]
        by = np.argsort(pair, kind="stable")
        which, pair = which[by], pair[by]
        first = np.flatnonzero(np.concatenate([[True], pair[1:] != pair[:-1]]))
        lowest = np.repeat(np.minimum.reduceat(docs[which], first), np.diff(np.append(first, len(which))))
        hit = which[docs[which] > lowest]
        marks[hit] |= np.int64(1) << (place[hit] - j)
    return marks


def _meet_segments(length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, rows = None, []

        def meet() -> pa.RecordBatch | None:
            if not rows:
                return None
            text = np.frombuffer(b"".join(r[0] for r in rows), np.uint8)
            keys, docs, marks = meet_segments(text, *(np.concatenate([unplanes(r[k]) for r in rows]) for k in (1, 2, 3)), length)
            return _flat(docs, key=keys, mark=marks) if len(keys) else None

        for batch in batches:
            for b, kind, *x in values(batch, "bucket", "kind", "text", "sizes", "places", "docs"):
                if b != here:
                    if (made := meet()) is not None:
                        yield made
                    here, rows = b, []
                if kind:
                    keys, docs = unpack(x[0]), unplanes(x[3])
                    yield _flat(docs, key=keys, mark=np.full(len(keys), _ALL, np.int64))
                else:
                    rows.append(x)
        if (made := meet()) is not None:
            yield made
        tidy()

    return run


# --- step 3: what stays -----------------------------------------------------------


def _drop(length: int, shared, with_text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, data, offsets in chunks(batches, "text", 1 << 20):
            gone = np.zeros(len(data) + 1, np.int32)
            row, (keys, marks) = _told(rows.column(rows.schema.get_field_index("told")), "key", "mark")
            if len(row):
                found = Segments(data, offsets, length, shared.value)
                pair = _pairs(row, keys.view(np.uint64))
                order = np.argsort(pair, kind="stable")
                pair, marks = pair[order], marks[order]
                first = np.flatnonzero(np.concatenate([[True], pair[1:] != pair[:-1]]))
                pair, marks = pair[first], np.bitwise_or.reduceat(marks, first)
                mine = _pairs(found.row, found.key)
                spot = np.minimum(np.searchsorted(pair, mine), len(pair) - 1)
                hit = np.flatnonzero(pair[spot] == mine)
                n = found.hi[hit] - found.lo[hit] + 1
                start = gather(found.lo[hit], n)
                bit = start - np.repeat(found.lo[hit], n)
                start = start[np.repeat(marks[spot[hit]], n) >> bit & 1 == 1]
                gone += np.bincount(start, minlength=len(gone)).astype(np.int32)
                gone -= np.bincount(start + length, minlength=len(gone)).astype(np.int32)
            copies = np.flatnonzero(rows.column(rows.schema.get_field_index("copy")).to_numpy(zero_copy_only=False).astype(bool) & (np.diff(offsets) >= length))
            np.add.at(gone, offsets[copies], 1)
            np.add.at(gone, offsets[copies + 1], -1)
            cover = np.cumsum(gone[:-1]) > 0
            opens = cover.copy()
            opens[1:] &= ~cover[:-1]
            heads = offsets[:-1][offsets[:-1] < len(data)]
            opens[heads] = cover[heads]
            sums = lambda x: np.diff(np.concatenate([[0], np.cumsum(x)])[offsets])
            removed = sums(cover)
            rest = np.ascontiguousarray(data[~cover])
            ends = np.concatenate([[0], np.cumsum(np.diff(offsets) - removed)])
            raw = memoryview(rest)
            digests = [hashlib.sha256(raw[a:b]).hexdigest() for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]
            out = [rows.column(rows.schema.get_field_index("doc_id")), pa.array(np.diff(offsets)), pa.array(removed.astype(np.int64)), pa.array(sums(opens).astype(np.int64)), pa.array(digests, pa.string())]
            kept = [pa.array([bytes(raw[a:b]) for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)], pa.binary())] if with_text else []
            yield pa.RecordBatch.from_arrays([*out, *kept], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", *(["kept"] if with_text else [])])

    return run


def _common(docs: DataFrame, length: int) -> HashIndex:
    """Anchors that a sample finds in many documents: at most a document's anchors over the share."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, data, offsets in chunks(batches, "text", 1 << 20):
            found = Segments(data, offsets, length)
            if len(found.row):
                pair = np.unique(_pairs(found.row, found.route), return_index=True)[1]
                yield pa.RecordBatch.from_arrays([pa.array(found.route[pair].view(np.int64))], names=["anchor"])

    sample = docs.filter(F.pmod(F.xxhash64("doc_id"), F.lit(SAMPLE)) == 0)
    least = max(COMMON_LEAST, int(sample.count() * COMMON_SHARE))
    rows = sample.select("text").mapInArrow(run, "anchor long").groupBy("anchor").agg(F.count("*").alias("n")).filter(F.col("n") >= least).select("anchor").collect()
    index = HashIndex(max(1, len(rows)))
    index.add(np.unique(np.array([r["anchor"] for r in rows], np.int64).view(np.uint64)))
    return index


def remove_repeats(docs: DataFrame, length: int = LENGTH, with_text: bool = False) -> DataFrame:
    """Per document (doc_id, text): n_bytes, n_removed, n_spans, kept_sha256, and with `with_text` the kept bytes."""
    if not ANCHOR < length <= ANCHOR + 62:
        raise ValueError(f"the length must be over {ANCHOR} and at most {ANCHOR + 62}")
    spark = docs.sparkSession
    parts = partitions(spark)
    texts = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    shared = spark.sparkContext.broadcast(_common(texts, length))
    deal = lambda df: df.repartition(parts, "bucket").sortWithinPartitions("bucket")

    prints = texts.filter("doc_id is not null").select("doc_id", F.sha2("text", 256).alias("print"), F.xxhash64("text").alias("mark"))
    first = prints.groupBy("print").agg(F.min("doc_id").alias("first"), F.count("*").alias("n")).filter("n > 1").drop("n")
    copies = prints.join(first, "print").filter("doc_id > first").groupBy("doc_id").agg(F.collect_set("mark").alias("copies"))
    # one exchange of the texts by id serves all three passes: left joins, and rows without an id are left out by the tasks
    known = texts.repartition(parts, "doc_id").join(copies, "doc_id", "left").select("doc_id", "text", F.coalesce(F.array_contains("copies", F.xxhash64("text")), F.lit(False)).alias("copy"))

    takes = known.filter("not copy")
    met = deal(takes.select("doc_id", "text").mapInArrow(_send_anchors(ANCHOR_BUCKETS * parts, length, shared), _SENT)).mapInArrow(_meet_anchors, _TOLD)
    told = met.groupBy("doc_id").agg(F.collect_list("key").alias("told"))
    sent = takes.join(told, "doc_id", "left").select("doc_id", "text", "told").mapInArrow(_send_segments(SEGMENT_BUCKETS * parts, length, shared), _SEGMENT)
    marked = deal(sent).mapInArrow(_meet_segments(length), _MARKS)
    back = marked.groupBy("doc_id").agg(F.collect_list(F.struct("key", "mark")).alias("told"))
    final = known.join(back, "doc_id", "left").select("doc_id", "text", "told", "copy")
    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", kept binary" if with_text else "")
    return final.mapInArrow(_drop(length, shared, with_text), schema)
