"""Near duplicates by circulant MinHash, banding, exact Jaccard and connected components.

Two permutations of 32-bit positions give all coordinates of a signature: the first
places a shingle, the second is read at that place shifted by 1, 2, ..., K. Equal shingle
sets are one node. Nodes that share a band are candidates:

1. each is held against the first node of its bucket (stars), and components are taken;
2. buckets that still hold several components drop, by their signatures, the members that
   resemble no member of another component (six standard deviations below the threshold);
3. what is left of a bucket meets in blocks with its full texts, members outside the
   bucket's main component against all, and each block returns links between components
   only, as many as a spanning forest has.

Every link is confirmed on the full shingle sets, and the components of the links are the
groups. No step returns more rows than it has members, apart from the blocks of a bucket
that more than BLOCK members, or BLOCK_SHINGLES shingles, outside its main component share.

Null and empty texts, and texts without words, have the empty set and stand alone; with
fewer words than a shingle has, the whole text is one shingle. Rows that repeat a doc_id
are documents of their own with that id, equal ones and different ones alike. A null
doc_id takes part; as `component_id` it counts after all others, and a group of such rows
alone has a null one.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from radarlake.llm.common import chunks, grams, mix, named, partitions, release, stored, unused, word_hashes

BANDS, ROWS = 32, 5
#: Members of a bucket in one block, and shingles of their sets, about; a group compares two blocks.
BLOCK, BLOCK_SHINGLES = 2048, 1 << 21
#: Members that one leader's text is read for at once.
STAR = 1024


def _mix32(x: np.ndarray) -> np.ndarray:
    x ^= x >> np.uint32(16)
    x *= np.uint32(0x7FEB352D)
    x ^= x >> np.uint32(15)
    x *= np.uint32(0x846CA68B)
    x ^= x >> np.uint32(16)
    return x


def shingle_sets(data: np.ndarray, offsets: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of each row after each other, and the offsets of the rows."""
    hashed, before = word_hashes(data, offsets)
    all_, at = grams(hashed, before, n)
    out = []
    for a, b, x, y in zip(at[:-1].tolist(), at[1:].tolist(), before[:-1].tolist(), before[1:].tolist(), strict=True):
        if b > a:
            out.append(np.unique(all_[a:b]))
        elif y > x:
            out.append(grams(hashed[x:y], np.array([0, y - x]), y - x)[0])
        else:
            out.append(all_[:0])
    return np.concatenate([all_[:0], *out]), np.concatenate([[0], np.cumsum([len(x) for x in out])]).astype(np.int64)


def signatures(sets: np.ndarray, at: np.ndarray, size: int) -> np.ndarray:
    """Signature (row, coordinate) of each set; rows with the empty set have the largest value everywhere."""
    out = np.full((len(at) - 1, size), 0xFFFFFFFF, np.uint32)
    full = np.flatnonzero(np.diff(at) > 0)
    if len(full):
        place = (mix(sets) >> np.uint64(32)).astype(np.uint32)
        for k in range(size):
            out[full, k] = np.minimum.reduceat(_mix32(place + np.uint32(k + 1)), at[full])
    return out


def _sign(n: int, bands: int, rows: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, data, offsets in chunks(batches, "text", 1 << 20):
            sets, at = shingle_sets(data, offsets, n)
            size = np.diff(at)
            full = np.flatnonzero(size > 0)
            prints = np.zeros((len(size), 2), np.uint64)
            for k, seed in enumerate((0x243F6A8885A308D3, 0x13198A2E03707344)):
                if len(full):
                    prints[full, k] = np.add.reduceat(mix(sets ^ np.uint64(seed)), at[full])
            signed = signatures(sets, at, bands * rows)
            band = np.zeros((len(size), bands), np.uint64)
            for j in range(bands):
                h = np.full(len(size), np.uint64(j + 1), np.uint64)
                for k in range(rows):
                    h = mix(h * np.uint64(0x9FB21C651E98DF25) + signed[:, j * rows + k].astype(np.uint64))
                band[:, j] = h
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(size) + 1) * bands, pa.int32()), pa.array(band.reshape(-1).view(np.int64)))
            yield pa.RecordBatch.from_arrays(
                [
                    *(b.column(b.schema.get_field_index(c)) for c in ("doc_id", "row_a", "row_b")),
                    pa.array(size), pa.array(prints[:, 0].view(np.int64)), pa.array(prints[:, 1].view(np.int64)), lists,
                    pa.array([x.tobytes() for x in signed.astype(np.uint8)], pa.binary()),
                ],
                names=["doc_id", "row_a", "row_b", "n_shingles", "print_a", "print_b", "bands", "sketch"],
            )

    return run


def row_key() -> list[Column]:
    """Two hashes of a row's id and text, which tell rows apart that share an id."""
    return [F.xxhash64("doc_id", "text").alias("row_a"), F.xxhash64("text", F.lit(1), "doc_id").alias("row_b")]


def sign(docs: DataFrame, n: int, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """Per document: the row's key, set size, a 128-bit print of the set, band hashes, and a byte of each coordinate."""
    given = docs.select("doc_id", *row_key(), "text")
    return given.mapInArrow(_sign(n, bands, rows), "doc_id long, row_a long, row_b long, n_shingles long, print_a long, print_b long, bands array<long>, sketch binary")


def _common(one: np.ndarray, other: np.ndarray) -> int:
    return len(np.intersect1d(one, other, assume_unique=True))


def _stars(n: int, percent: int):
    """Links (a, b) of members to their leader; a leader's row comes before its members' rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        led, leader = None, None
        for rows, data, offsets in chunks(batches, "text", 1 << 19):
            sets, at = shingle_sets(data, offsets, n)
            key, node = (rows.column(rows.schema.get_field_index(c)).to_pylist() for c in ("leader", "node"))
            a, b = [], []
            for i, (k, m) in enumerate(zip(key, node, strict=True)):
                mine = sets[at[i] : at[i + 1]]
                if k == m:
                    led, leader = k, mine.copy()
                elif k == led:
                    both = _common(mine, leader)
                    if both and 100 * both >= percent * (len(mine) + len(leader) - both):
                        a.append(m)
                        b.append(k)
            if a:
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return run


def _sketched(least: int):
    """Members (bucket, node) of open buckets that at least one member of another component resembles.

    Blocks (bucket, i, j) as in `_exact`; what a block's members resemble is told for both sides.
    """

    def meet(bucket: int, node: np.ndarray, component: np.ndarray, own: np.ndarray, sketch: np.ndarray) -> pa.RecordBatch | None:
        mine, rest = np.flatnonzero(own), np.flatnonzero(~own)
        near = np.zeros(len(node), bool)
        for i in mine.tolist():
            met = ((sketch[rest] == sketch[i]).sum(1) >= least) & (component[rest] != component[i])
            near[i] = met.any()
            near[rest[met]] = True
        found = np.unique(node[near])
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(found), bucket)), pa.array(found)], names=["bucket", "node"]) if len(found) else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, parts in _blocks(batches, ("node", "component", "own", "sketch")):
            node, component, own, sketch = (np.concatenate(x) for x in zip(*parts, strict=True))
            if (made := meet(key[0], node, component, own, sketch)) is not None:
                yield made

    return run


def _blocks(batches: Iterator[pa.RecordBatch], names: tuple[str, ...]):
    """Rows of each (bucket, i, j) in turn: per batch the named columns as arrays, a sketch as a matrix."""
    here, parts = None, []
    for batch in batches:
        get = lambda c: batch.column(batch.schema.get_field_index(c))  # noqa: E731, B023
        keys = np.stack([get(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("bucket", "i", "j")], 1)
        edge = np.flatnonzero(np.concatenate([[True], (keys[1:] != keys[:-1]).any(1)])) if len(keys) else np.zeros(0, np.int64)
        for a, b in zip(edge.tolist(), [*edge[1:].tolist(), len(keys)], strict=False):
            key = tuple(keys[a].tolist())
            if key != here:
                if parts:
                    yield here, parts
                here, parts = key, []
            part = []
            for c in names:
                column = get(c).slice(a, b - a)
                if pa.types.is_binary(column.type):
                    part.append(np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(b - a, -1))
                else:
                    part.append(column.to_numpy(zero_copy_only=False))
            parts.append(part)
    if parts:
        yield here, parts


def spanning(sets: list[np.ndarray], node: np.ndarray, component: np.ndarray, own: np.ndarray, percent: int) -> tuple[list[int], list[int]]:
    """Links between components that reach the threshold, of own members against the others; those that join nothing new are left out."""
    rest = np.flatnonzero(~own)
    size = np.array([len(sets[i]) for i in rest.tolist()], np.int64)
    all_ = np.concatenate([np.zeros(0, np.uint64), *(sets[i] for i in rest.tolist())])
    order = np.argsort(all_, kind="stable")
    all_, holder = all_[order], np.repeat(np.arange(len(rest)), size)[order]
    root = {c: c for c in component.tolist()}

    def find(c: int) -> int:
        while root[c] != c:
            root[c] = c = root[root[c]]
        return c

    a, b = [], []
    for i in np.flatnonzero(own).tolist():
        lo, hi = np.searchsorted(all_, sets[i], "left"), np.searchsorted(all_, sets[i], "right")
        k = hi - lo
        met = holder[np.repeat(lo - (np.cumsum(k) - k), k) + np.arange(k.sum())]
        both = np.bincount(met, minlength=len(rest))
        for j in np.flatnonzero((both > 0) & (100 * both >= percent * (len(sets[i]) + size - both)) & (component[rest] != component[i])).tolist():
            x, y = find(int(component[i])), find(int(component[rest[j]]))
            if x != y:
                root[max(x, y)] = min(x, y)
                a.append(int(node[i]))
                b.append(int(node[rest[j]]))
    return a, b


def _exact(n: int, percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, sets, fields = None, [], []

        def meet() -> pa.RecordBatch | None:
            a, b = spanning(sets, *(np.concatenate(x) for x in zip(*fields, strict=True)), percent) if fields else ([], [])
            return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"]) if a else None

        for rows, data, offsets in chunks(batches, "text", 1 << 19):
            found, at = shingle_sets(data, offsets, n)
            for key, parts in _blocks(iter([rows.append_column("nth", pa.array(np.arange(rows.num_rows)))]), ("node", "component", "own", "nth")):
                if key != here:
                    if (made := meet()) is not None:
                        yield made
                    here, sets, fields = key, [], []
                for *field, nth in parts:
                    fields.append(field)
                    sets += [found[at[i] : at[i + 1]].copy() for i in nth.tolist()]
        if (made := meet()) is not None:
            yield made

    return run


def _labelled(places: DataFrame, found: DataFrame) -> DataFrame:
    """(bucket, node, component, apart, blocks) of the buckets (bucket, node, n_shingles) with several components; apart: outside the bucket's main one."""
    labelled = places.join(found, places["node"] == found["id"], "left").select("bucket", "node", "n_shingles", F.coalesce("component", "node").alias("component"))
    parts = labelled.groupBy("bucket", "component").agg(F.count("*").alias("k"), F.sum("n_shingles").alias("z"))
    largest = F.struct("k", "component", "z")
    main = parts.groupBy("bucket").agg(F.max(largest).alias("main"), F.count("*").alias("parts"), F.sum("k").alias("n"), F.sum("z").alias("all")).filter("parts > 1")
    blocks = lambda n, z: F.greatest(F.ceil(n / BLOCK), F.ceil(z / BLOCK_SHINGLES)).cast("int")
    sizes = main.select("bucket", "main.component", blocks(F.col("n") - F.col("main.k"), F.col("all") - F.col("main.z")).alias("i_blocks"), blocks(F.col("n"), F.col("all")).alias("j_blocks")).withColumnRenamed("component", "main")
    return labelled.join(sizes, "bucket").select("bucket", "node", "component", (F.col("component") != F.col("main")).alias("apart"), "i_blocks", "j_blocks")


def _dealt(rows: DataFrame, *more: str) -> DataFrame:
    """Members of open buckets by (bucket, i, j): those apart, as own, in block i against all members in block j."""
    home = lambda n: F.pmod(F.xxhash64("node"), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    own = rows.filter("apart").select("bucket", home("i_blocks").alias("i"), every("j_blocks").alias("j"), F.lit(True).alias("own"), "node", "component", *more)
    rest = rows.select("bucket", every("i_blocks").alias("i"), home("j_blocks").alias("j"), F.lit(False).alias("own"), "node", "component", *more)
    return own.unionByName(rest).repartition(partitions(rows.sparkSession), "bucket", "i", "j").sortWithinPartitions("bucket", "i", "j")


def links(nodes: DataFrame, docs: DataFrame, n: int, percent: int, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """Confirmed links (a, b) that connect all nodes (node, row_a, row_b, n_shingles, bands, sketch) whose sets reach the threshold.

    `docs` holds the texts of the nodes' rows. A pair within a component needs no check.
    """
    members = nodes.select("node", "n_shingles", F.explode("bands").alias("bucket"))
    # buckets with the same members count once
    seen = [F.bit_xor(F.xxhash64("node", F.lit(k))).alias(f"x{k}") for k in range(2)]
    buckets = members.groupBy("bucket").agg(F.min("node").alias("leader"), F.count("*").alias("n"), *seen).filter("n > 1")
    buckets = buckets.groupBy("leader", "n", "x0", "x1").agg(F.min("bucket").alias("bucket")).select("bucket", "leader", "n")
    places = stored(members.join(buckets, "bucket"), "buckets")
    # the texts that any check may need, dealt out once
    wanted = nodes.join(places.select("node").distinct(), "node", "left_semi").select("node", "row_a", "row_b")
    texts = stored(docs.select(*row_key(), "text").join(wanted, ["row_a", "row_b"]).select("node", "text").dropDuplicates(["node"]), "texts")
    # a leader's text is read once for about STAR members, whatever the number of its buckets
    led = places.filter("node > leader").groupBy("leader", "node").agg(F.max("n").alias("n"))
    salts = F.ceil(F.max("n") / STAR).cast("int")
    leaders = led.groupBy("leader").agg(salts.alias("salts"))
    salted = led.join(leaders, "leader").select("leader", F.pmod(F.xxhash64("node"), F.col("salts")).cast("int").alias("salt"), "node")
    heads = leaders.select("leader", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"), F.col("leader").alias("node"))
    read = salted.unionByName(heads).join(texts, "node")
    dealt = read.repartition(partitions(docs.sparkSession), "leader", "salt").sortWithinPartitions("leader", "salt", F.col("node") != F.col("leader"))
    first = stored(dealt.select("leader", "node", "text").mapInArrow(_stars(n, percent), "a long, b long"), "links")
    # buckets of two are settled by now
    found = stored(components(first), "components")
    share, size = percent / 100, bands * rows
    least = int(share * size - 6 * (share * (1 - share) * size) ** 0.5)
    open_ = stored(_labelled(places.filter("n > 2").select("bucket", "node", "n_shingles"), found), "open")
    sketched = _dealt(open_.join(nodes.select("node", "sketch"), "node"), "sketch").mapInArrow(_sketched(least), "bucket long, node long").distinct()
    near = stored(_labelled(sketched.join(nodes.select("node", "n_shingles"), "node"), found), "near")
    second = stored(_dealt(near.join(texts, "node"), "text").mapInArrow(_exact(n, percent), "a long, b long").distinct(), "links")
    release(places, texts, open_, near, found)
    return first.unionByName(second)


def components(edges: DataFrame, rounds: int = 50) -> DataFrame:
    """(id, component): the smallest id reachable over undirected links (a, b), for each id that has a link.

    Large and small stars in turn: each step hangs neighbours on their smallest neighbour,
    with sums before every exchange; ends when a round changes nothing. Only the last
    round's table is kept.
    """
    here = stored(edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    state = None
    for _ in range(rounds):
        both = here.unionByName(here.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("low")).select("a", F.least("a", "low").alias("low"))
        large = both.filter("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("low").alias("b")).filter("a <> b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("low"))
        small = large.join(low, "a")
        hung = small.select(F.col("b").alias("a"), F.col("low").alias("b")).filter("a <> b").unionByName(low.select("a", F.col("low").alias("b"))).distinct()
        before, here = here, stored(hung, "edges")
        release(before)
        now = here.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
        if now == state:
            break
        state = now
    else:
        raise RuntimeError(f"the components did not settle in {rounds} rounds")
    return here.select(F.col("a").alias("id"), F.col("b").alias("component")).unionByName(here.select(F.col("b").alias("id"), F.col("b").alias("component")).distinct())


def groups(docs: DataFrame, n: int = 5, percent: int = 80, bands: int = BANDS, rows: int = ROWS, keys: bool = False) -> DataFrame:
    """Per document (doc_id, text): n_shingles, component_id, kept; with `keys` also the row's key and whether it is the one row that stands for its group."""
    signed = stored(sign(docs, n, bands, rows), "signatures")
    who = F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "row_a", "row_b")
    same = signed.filter("n_shingles > 0").groupBy("print_a", "print_b").agg(F.min(who).alias("first"), F.count("*").alias("n"))
    same = stored(same.withColumn("node", F.monotonically_increasing_id()), "sets")
    one = same.select("node", F.col("first.row_a").alias("row_a"), F.col("first.row_b").alias("row_b"))
    nodes = stored(signed.select("row_a", "row_b", "n_shingles", "bands", "sketch").join(one, ["row_a", "row_b"]).dropDuplicates(["node"]), "nodes")
    found = components(links(nodes, docs, n, percent, bands, rows))
    linked = found.join(same.select("node", "first"), F.col("id") == F.col("node")).select("node", "component", "first")
    heads = linked.groupBy("component").agg(F.min("first").alias("head"))
    linked = linked.join(heads, "component").select("node", "head")
    # sets of one row without a link are their own group
    placed = same.join(linked, "node", "left").filter("n > 1 or head is not null").select("print_a", "print_b", F.coalesce("head", "first").alias("head"))
    out = signed.select("doc_id", "row_a", "row_b", "n_shingles", "print_a", "print_b").join(placed, ["print_a", "print_b"], "left")
    # the empty set has no entry
    component = F.when(F.col("head").isNull(), F.col("doc_id")).otherwise(F.col("head.doc_id"))
    stands = F.col("head").isNull() | ((F.col("row_a") == F.col("head.row_a")) & (F.col("row_b") == F.col("head.row_b")))
    more = ["row_a", "row_b", stands.alias("stands")] if keys else []
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.col("doc_id").eqNullSafe(component).alias("kept"), *more)


def keep_one(docs: DataFrame, n: int = 5, percent: int = 80) -> DataFrame:
    """The rows of `docs` without near duplicates: of each group the row with the smallest id, and of equal rows one."""
    keys = unused(docs, "row_a", "row_b")
    found = groups(docs.select("doc_id", "text"), n, percent, keys=True).filter("stands").select("row_a", "row_b").distinct().toDF(*keys)
    held = docs.select("*", *(c.alias(k) for c, k in zip(row_key(), keys, strict=True)))
    return held.join(found, keys, "left_semi").dropDuplicates(keys).select(*named(docs))
