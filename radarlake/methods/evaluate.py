"""Caption and retrieval measures."""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


#: Vectors of a block of queries and of the corpus, and queries that are scored at once.
QUERY_BLOCK, CORPUS_BLOCK, AT_ONCE = 1024, 32_768, 64


def _best(k: int, own: bool):
    """The k best of a corpus block for each query of a query block."""

    def run(q: pa.Table, c: pa.Table) -> pa.Table:
        flat = lambda t, n: np.concatenate([x.flatten().to_numpy(zero_copy_only=False) for x in t[n].chunks]).astype(np.float64).reshape(t.num_rows, -1)
        rows, cols, scores = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)]
        if q.num_rows and c.num_rows:
            a, b = flat(q, "asked"), flat(c, "held")
            asked, ids = q["query"].to_numpy(), c["hit"].to_numpy()
            for low in range(0, len(a), AT_ONCE):
                s = a[low : low + AT_ONCE] @ b.T
                if not own:
                    s[asked[low : low + AT_ONCE, None] == ids[None, :]] = -np.inf
                r = np.round(s, 9)
                least = np.partition(r, max(len(b) - k, 0), axis=1)[:, max(len(b) - k, 0)]
                for i in range(len(r)):
                    at = np.flatnonzero((r[i] >= least[i]) & (r[i] > -np.inf))
                    at = at[np.lexsort((ids[at], -r[i, at]))[:k]]
                    rows.append(np.full(len(at), low + i))
                    cols.append(at)
                    scores.append(s[i, at])
        x, y = np.concatenate(rows), np.concatenate(cols)
        found = [*(q[n].take(x) for n in ("query", "query_label")), *(c[n].take(y) for n in ("hit", "hit_label")), pa.array(np.concatenate(scores))]
        return pa.table(found, names=["query", "query_label", "hit", "hit_label", "score"])

    return run


def retrieval(queries: DataFrame, corpus: DataFrame, k: int, own: bool = True) -> DataFrame:
    """The k best vectors of the corpus for each query by inner product; scores equal to nine digits tie by id.

    Each block of queries meets each block of the corpus in a task of its own, which keeps its best k of
    each query before the exchange. A query's own row is a hit like any other, or none if `own` is false.
    """
    blocks = lambda df, size: -(-df.count() // size) or 1
    nq, nc = blocks(queries, QUERY_BLOCK), blocks(corpus, CORPUS_BLOCK)
    dealt = lambda n: F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    q = queries.select(F.col("vec_id").alias("query"), F.col("label").alias("query_label"), F.col("embedding").alias("asked"), dealt(nq).alias("_q"), every(nc).alias("_c"))
    c = corpus.select(F.col("vec_id").alias("hit"), F.col("label").alias("hit_label"), F.col("embedding").alias("held"), dealt(nc).alias("_c"), every(nq).alias("_q"))
    kind = dict(corpus.dtypes)
    schema = ", ".join(f"{n} {kind[t]}" for n, t in (("query", "vec_id"), ("query_label", "label"), ("hit", "vec_id"), ("hit_label", "label"))) + ", score double"
    s = q.groupBy("_q", "_c").cogroup(c.groupBy("_q", "_c")).applyInArrow(_best(k, own), schema)
    order = Window.partitionBy("query").orderBy(F.desc(F.round("score", 9)), "hit")
    return s.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def recall(ranked: DataFrame) -> DataFrame:
    """Share of queries with a hit of their label at 1 and within the ranks given, and the mean reciprocal rank."""
    same = F.col("query_label") == F.col("hit_label")
    one = ranked.groupBy("query").agg(F.max((same & (F.col("rank") == 1)).cast("int")).alias("a"), F.max(same.cast("int")).alias("b"), F.coalesce(F.max(F.when(same, 1 / F.col("rank"))), F.lit(0.0)).alias("rr"))
    return one.agg(F.count("*").alias("queries"), F.avg("a").alias("recall_1"), F.avg("b").alias("recall_10"), F.avg("rr").alias("mrr"))


def unigram(pairs: DataFrame, keys: list[str]) -> DataFrame:
    """Precision and recall of the candidate's words against the reference's, counted with repetition."""
    count = lambda c, n: pairs.select(*keys, F.explode(F.split(F.lower(c), " ")).alias("w")).groupBy(*keys, "w").agg(F.count("*").alias(n))
    j = count("reference", "a").join(count("candidate", "b"), [*keys, "w"], "full")
    z = lambda c: F.coalesce(F.col(c), F.lit(0))
    s = j.groupBy(*keys).agg(F.sum(F.least(z("a"), z("b"))).alias("hit"), F.sum("a").alias("a"), F.sum("b").alias("b"))
    return s.select(*keys, F.try_divide("hit", "b").alias("precision"), F.try_divide("hit", "a").alias("recall"))


def lcs(a: list[str], b: list[str]) -> int:
    """Length of the longest common subsequence; a bit of one number for each word of `a`, so a word of `b` is one step."""
    where: dict[str, int] = {}
    for i, x in enumerate(a):
        where[x] = where.get(x, 0) | 1 << i
    open_, full = (1 << len(a)) - 1, (1 << len(a)) - 1
    for y in b:
        met = open_ & where.get(y, 0)
        open_ = ((open_ + met) | (open_ - met)) & full
    return len(a) - open_.bit_count()


def rouge_l(pairs: DataFrame, beta: float = 1.2) -> DataFrame:
    """F measure of the longest common word sequence of `reference` and `candidate`."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            get = lambda n: b.column(b.schema.get_field_index(n)).to_pylist()  # noqa: E731, B023
            out = []
            for r, c in zip(get("reference"), get("candidate"), strict=True):
                r, c = (r or "").lower().split(), (c or "").lower().split()
                n = lcs(r, c)
                p, q = n / max(len(c), 1), n / max(len(r), 1)
                out.append((1 + beta**2) * p * q / (q + beta**2 * p) if n else 0.0)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(out, pa.float64())], names=[*b.schema.names, "rouge_l"])

    schema = ", ".join(f"`{c}` {t}" for c, t in pairs.dtypes)
    return pairs.mapInArrow(run, f"{schema}, rouge_l double")


def meteor_exact(reference: list[str], candidate: list[str]) -> float:
    """METEOR's exact stage: 10PR / (R + 9P), less a penalty for the pieces that the matches fall into; each word matches its first free equal, in order."""
    free: dict[str, list[int]] = {}
    for i, w in enumerate(reference):
        free.setdefault(w, []).append(i)
    used = dict.fromkeys(free, 0)
    places = []
    for w in candidate:
        k = used.get(w)
        if k is not None and k < len(free[w]):
            places.append(free[w][k])
            used[w] = k + 1
        else:
            places.append(None)
    m = sum(p is not None for p in places)
    if not m:
        return 0.0
    chunks = sum(p is not None and (i == 0 or places[i - 1] is None or places[i - 1] + 1 != p) for i, p in enumerate(places))
    p, r = m / len(candidate), m / len(reference)
    return 10 * p * r / (r + 9 * p) * (1 - 0.5 * (chunks / m) ** 3)


#: Dimensions of the stand-in word vectors.
DIMENSIONS = 32


def hashed_vectors(words: list[str]) -> np.ndarray:
    """Stand-in encoder: a unit vector of signs for each word, from its digest; equal words have equal vectors."""
    out = np.empty((len(words), DIMENSIONS))
    for i, w in enumerate(words):
        raw = np.frombuffer(hashlib.blake2b(w.encode(), digest_size=DIMENSIONS // 8).digest(), np.uint8)
        out[i] = np.unpackbits(raw) * 2.0 - 1.0
    return out / np.sqrt(DIMENSIONS)


def greedy_cosine(reference: list[str], candidate: list[str], encode: Callable[[list[str]], np.ndarray] = hashed_vectors) -> float:
    """F measure of each word's largest cosine on the other side, over the vectors of any encoder."""
    if not reference or not candidate:
        return 0.0
    cosine = encode(candidate) @ encode(reference).T
    p, r = cosine.max(1).mean(), cosine.max(0).mean()
    return float(2 * p * r / (p + r)) if p + r > 0 else 0.0


def captioning(pairs: DataFrame, encode: Callable[[list[str]], np.ndarray] = hashed_vectors) -> DataFrame:
    """All text measures of `reference` and `candidate` in one pass: unigram precision, recall and F1, ROUGE-L, METEOR's exact stage, greedy cosine."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            get = lambda n: b.column(b.schema.get_field_index(n)).to_pylist()  # noqa: E731, B023
            out = []
            for r, c in zip(get("reference"), get("candidate"), strict=True):
                r, c = (r or "").lower().split(), (c or "").lower().split()
                hit = sum((Counter(r) & Counter(c)).values())
                p, q, n = hit / max(len(c), 1), hit / max(len(r), 1), lcs(r, c)
                lp, lr = n / max(len(c), 1), n / max(len(r), 1)
                rouge = (1 + 1.44) * lp * lr / (lr + 1.44 * lp) if n else 0.0
                out.append((p, q, 2 * p * q / (p + q) if hit else 0.0, rouge, meteor_exact(r, c), greedy_cosine(r, c, encode)))
            made = list(zip(*out, strict=True)) or [()] * len(MEASURES)
            yield pa.RecordBatch.from_arrays([*b.columns, *(pa.array(x, pa.float64()) for x in made)], names=[*b.schema.names, *MEASURES])

    schema = ", ".join(f"`{c}` {t}" for c, t in pairs.dtypes)
    return pairs.mapInArrow(run, schema + "".join(f", {m} double" for m in MEASURES))


MEASURES = ("precision", "recall", "f1", "rouge_l", "meteor", "cosine")


def shifted(pairs: DataFrame, keys: list[str], candidate: str = "candidate") -> DataFrame:
    """Each pair with the next pair's candidate in the order of a hash of the keys, the last with the first's: no pair keeps its own if there are two or more.

    Places are counted inside ranges of the hash and moved by the ranges before, so that no task sorts all pairs.
    """
    from radarlake.methods.release import _running

    h = F.md5(F.concat_ws("-", *keys))
    ranged = pairs.withColumn("_h", h).withColumn("_part", F.substring("_h", 1, 2)).withColumn("_one", F.lit(1))
    placed = _running(ranged, "_one", ["_h", *keys], "_part").withColumnRenamed("before", "_place").drop("_h", "_part", "_one")
    n = F.broadcast(pairs.agg(F.count("*").alias("_n")))
    other = placed.crossJoin(n).select(F.pmod(F.col("_place") - 1, F.col("_n")).alias("_place"), F.col(candidate).alias("_other"))
    return placed.join(other, "_place").withColumn(candidate, F.col("_other")).drop("_place", "_other")


def control(matched: DataFrame, mismatched: DataFrame, score: str) -> DataFrame:
    """Mean score of matched and of mismatched pairs, their gap, and the chance that a matched pair scores higher (ties count half).

    Scores are counted by their value to four digits; the table of values has at most some ten thousand rows.
    """
    value = F.round(score, 4)
    both = matched.select(value.alias("v"), F.lit(1).alias("m")).unionByName(mismatched.select(value.alias("v"), F.lit(0).alias("m")))
    by = both.filter("v is not null").groupBy("v").agg(F.sum("m").alias("a"), F.sum(1 - F.col("m")).alias("b"))
    below = Window.partitionBy(F.lit(1)).orderBy("v").rowsBetween(Window.unboundedPreceding, -1)
    wins = by.withColumn("won", F.col("a") * (F.coalesce(F.sum("b").over(below), F.lit(0)) + F.col("b") / 2))
    a, b = F.sum("a"), F.sum("b")
    mean = lambda k, n: F.sum(F.col("v") * F.col(k)) / n
    return wins.agg(a.alias("pairs"), mean("a", a).alias("matched"), mean("b", b).alias("mismatched"), (mean("a", a) - mean("b", b)).alias("gap"), F.try_divide(F.sum("won"), a * b).alias("auc"))


def judged(df: DataFrame, verdict: Column, truth: str) -> DataFrame:
    """Agreement of a judge (any column of 0 and 1) with given labels: counts of each pair of values and the share that agrees."""
    n = df.select(verdict.cast("int").alias("judged"), F.col(truth).alias("truth")).groupBy("truth", "judged").agg(F.count("*").alias("n"))
    whole = Window.partitionBy(F.lit(1))  # four rows
    return n.withColumn("agreement", F.sum(F.when(F.col("truth") == F.col("judged"), F.col("n")).otherwise(0)).over(whole) / F.sum("n").over(whole))


def category_f1(a: Column, b: Column) -> Column:
    """F1 of two sets of categories, 1 for two empty ones: a stand-in judge of meaning."""
    both = F.size(F.array_intersect(a, b))
    return F.when((F.size(a) == 0) & (F.size(b) == 0), 1.0).otherwise(F.coalesce(F.try_divide(2.0 * both, (F.size(a) + F.size(b)).cast("double")), F.lit(0.0)))


def retention(df: DataFrame, slices: list[str], before: str, after: str) -> DataFrame:
    """Mean score by slice before and after, and the share that is kept."""
    b, a = F.avg(before), F.avg(after)
    return df.groupBy(*slices).agg(F.count("*").alias("n"), b.alias("before"), a.alias("after"), F.try_divide(a, b).alias("kept"))


def by_sensor(df: DataFrame, slice_: str, sensor: str, values: list[str], score: str) -> DataFrame:
    """Mean score by slice, a column for each sensor."""
    return df.groupBy(slice_).pivot(sensor, values).agg(F.avg(score))


def attachment(df: DataFrame, trained: str, other: str, by: list[str]) -> DataFrame:
    """Paired difference of the scores under the instruction of the training and under another one."""
    d = F.col(trained) - F.col(other)
    return df.groupBy(*by).agg(F.count("*").alias("n"), F.avg(d).alias("difference"), F.avg((d > 0).cast("int")).alias("better"))


def protocol(version: str, **tables: DataFrame) -> DataFrame:
    """One table (version, task, metric, value) from one-row frames of measures."""
    rows = None
    for task, t in sorted(tables.items()):
        one = t.select(F.lit(version).alias("version"), F.lit(task).alias("task"), F.explode(F.create_map(*(x for c in t.columns for x in (F.lit(c), F.col(c).cast("double"))))).alias("metric", "value"))
        rows = one if rows is None else rows.unionByName(one)
    return rows


#: Tables and bits of the hyperplane index.
TABLES, BITS = 24, 7


def _codes(vectors: np.ndarray, tables: int, bits: int, probes: bool) -> list[np.ndarray]:
    """Numbers of the buckets of each vector, a column a table; with `probes` also those a flip of one bit away."""
    planes = np.random.Generator(np.random.PCG64(20)).standard_normal((vectors.shape[1], tables * bits))
    bit = (vectors @ planes > 0).reshape(len(vectors), tables, bits)
    own = (bit << np.arange(bits)).sum(2) + (np.arange(tables) << bits)
    return [own, *(own ^ (1 << k) for k in range(bits))] if probes else [own]


def _buckets(df: DataFrame, tables: int, bits: int, probes: bool) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x = b.column(b.schema.get_field_index("embedding"))
            made = np.concatenate(_codes(x.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(b.num_rows, -1), tables, bits, probes), axis=1)
            at = pa.array(np.arange(b.num_rows + 1) * made.shape[1], pa.int32())
            yield pa.RecordBatch.from_arrays([*b.columns, pa.ListArray.from_arrays(at, pa.array(made.reshape(-1).astype(np.int32)))], names=[*b.schema.names, "buckets"])

    schema = ", ".join(f"`{c}` {t}" for c, t in df.dtypes)
    return df.filter(F.col("embedding").isNotNull()).mapInArrow(run, f"{schema}, buckets array<int>")


def retrieval_lsh(queries: DataFrame, corpus: DataFrame, k: int, tables: int = TABLES, bits: int = BITS) -> DataFrame:
    """Like `retrieval`, over the vectors that share a bucket of random hyperplanes with the query or lie one bit away.

    Every vector is in the index, and no bucket is cut; `lsh_recall` measures what is lost.
    A query meets a vector once, in the first bucket that both have.
    """
    q = _buckets(queries.select(F.col("vec_id").alias("query"), F.col("label").alias("query_label"), "embedding"), tables, bits, True)
    q = q.select("query", "query_label", F.col("embedding").alias("asked"), F.col("buckets").alias("probes"), F.explode("buckets").alias("bucket"))
    c = _buckets(corpus.select(F.col("vec_id").alias("hit"), F.col("label").alias("hit_label"), "embedding"), tables, bits, False)
    c = c.select("hit", "hit_label", F.col("embedding").alias("held"), F.col("buckets").alias("own"), F.explode("buckets").alias("bucket"))
    met = q.join(c, "bucket").filter(F.col("bucket") == F.array_min(F.array_intersect("probes", "own")))
    score = F.aggregate(F.zip_with("asked", "held", lambda a, b: a.cast("double") * b.cast("double")), F.lit(0.0), lambda s, x: s + x)
    order = Window.partitionBy("query").orderBy(F.desc(F.round("score", 9)), "hit")
    scored = met.select("query", "query_label", "hit", "hit_label", score.alias("score"))
    return scored.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def lsh_recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    """Share of the exact hits that were found."""
    hit = exact.select("query", "hit").join(found.select("query", "hit", F.lit(1).alias("_f")), ["query", "hit"], "left")
    return hit.agg(F.count("*").alias("hits"), F.avg(F.coalesce("_f", F.lit(0))).alias("recall"))
