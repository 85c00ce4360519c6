"""Data operations of the generation baseline, and a scaled-down stand-in for the generator itself.

The stand-in is a linear denoiser of small patches, one matrix a noise step, conditioned
on a class. It is fitted in closed form from sums that a single pass over the table
takes; the driver holds matrices of the patch's size alone. What the baseline does with a
large network (text to image, variants of a real image, in- and outpainting, an adapter
of low rank on a frozen base) is done with it in the same way.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Share of the signal's variance that is left after each noise step, the first one unnoised.
SCHEDULE = (1.0, 0.85, 0.6, 0.3, 0.08, 0.01)


def uniform(*parts: Column | str) -> Column:
    """A number in (0, 1) that follows from the parts, from the first eight digits of their MD5."""
    word = F.conv(F.substring(F.md5(F.concat_ws("-", *parts)), 1, 8), 16, 10).cast("double")
    return (word + 0.5) / float(1 << 32)


# --- augmentation, noise, masks, attention: expressions ---------------------------


def augment(df: DataFrame, epoch: int, p_drop: float, key: str = "sample_id", captions: str = "captions", variants: tuple[str, ...] = ("SHORT", "MID", "LONG"), prefix: str = "") -> DataFrame:
    """One caption of each sample for an epoch: a drawn variant, words dropped with a chance, a prefix. Key and epoch alone decide."""
    from radarlake.methods.geo import bound

    e = F.lit(str(epoch))
    drawn = F.least(F.floor(uniform(F.col(key).cast("string"), e) * len(variants)), F.lit(len(variants) - 1)).cast("int")
    name = F.element_at(F.array(*map(F.lit, variants)), drawn + 1)
    chosen = df.withColumn("variant", name)
    words = bound({"w": F.split(F.element_at(F.col(captions), F.col("variant")), " ")}, lambda s: F.filter(s["w"], lambda x, i: uniform(F.col(key).cast("string"), e, i.cast("string")) >= p_drop))
    return chosen.withColumn("text", F.concat(F.lit(prefix), F.array_join(words, " ")))


def noise(df: DataFrame, signal: float, seed: int, values: tuple[str, ...], keys: tuple[str, ...]) -> DataFrame:
    """Each value with normal noise: sqrt(signal) x + sqrt(1 - signal) e, where e follows from keys, column and seed by Box and Muller."""
    out = df
    for v in values:
        name = [F.col(k).cast("string") for k in keys]
        u1, u2 = uniform(*name, F.lit(v), F.lit(str(seed)), F.lit("a")), uniform(*name, F.lit(v), F.lit(str(seed)), F.lit("b"))
        e = F.sqrt(-2 * F.ln(u1)) * F.cos(F.lit(2 * np.pi) * u2)
        out = out.withColumn(v, F.col(v) * float(np.sqrt(signal)) + e * float(np.sqrt(1 - signal)))
    return out


MASKS = ("inpaint", "outpaint", "half")


def known(kind: str, size: int, r: Column, c: Column) -> Column:
    """Whether a cell of a patch is given: all but the middle, the middle alone, or the left half."""
    low, high = size // 4, size - size // 4
    middle = r.between(low, high - 1) & c.between(low, high - 1)
    return {"inpaint": ~middle, "outpaint": middle, "half": c < size // 2}[kind]


def attention(tokens: DataFrame, patches: DataFrame, token: str, patch: str, q: str = "q", k: str = "k") -> DataFrame:
    """Weights of each patch for each token: softmax over the patches of inner products over the root of the length. The tokens are few and sent to all."""
    inner = F.aggregate(F.zip_with(q, k, lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x) / F.sqrt(F.size(q).cast("double"))
    s = patches.crossJoin(F.broadcast(tokens)).select(token, patch, inner.alias("s"))
    top = s.groupBy(token).agg(F.max("s").alias("top"))
    e = s.join(F.broadcast(top), token).withColumn("e", F.exp(F.col("s") - F.col("top")))
    total = e.groupBy(token).agg(F.sum("e").alias("total"))
    return e.join(F.broadcast(total), token).select(token, patch, (F.col("e") / F.col("total")).alias("weight"))


# --- the stand-in generator -------------------------------------------------------


@dataclass(frozen=True)
class Denoiser:
    """Per noise step a matrix from (noisy patch, class, 1) to the clean patch, and an adapter's factors if there are any."""

    matrices: tuple[np.ndarray, ...]
    classes: int
    schedule: tuple[float, ...] = SCHEDULE
    adapter: tuple[tuple[np.ndarray, np.ndarray], ...] = ()

    def clean(self, x: np.ndarray, label: np.ndarray, step: int) -> np.ndarray:
        design = _design(x, label, self.classes)
        out = design @ self.matrices[step - 1]
        if self.adapter:
            left, right = self.adapter[step - 1]
            out = out + design @ left @ right
        return out

    def parameters(self) -> tuple[int, int]:
        """Numbers in the base and in the adapter."""
        return sum(m.size for m in self.matrices), sum(a.size + b.size for a, b in self.adapter)


def _design(x: np.ndarray, label: np.ndarray, classes: int) -> np.ndarray:
    return np.concatenate([x, np.eye(classes)[label], np.ones((len(x), 1))], 1)


def _normal(keys: list, step: int, seed: int, width: int) -> np.ndarray:
    """Noise that follows from a row's key, the step and the seed, wherever the row is worked on."""
    out = np.empty((len(keys), width))
    for i, k in enumerate(keys):
        number = int.from_bytes(hashlib.blake2b(f"{k}-{step}-{seed}".encode(), digest_size=8).digest(), "little")
        out[i] = np.random.Generator(np.random.PCG64(number)).standard_normal(width)
    return out


def _arrays(b: pa.RecordBatch, width: int) -> tuple[list, np.ndarray, np.ndarray]:
    get = lambda n: b.column(b.schema.get_field_index(n))
    return get("key").to_pylist(), get("label").to_numpy(zero_copy_only=False).astype(np.int64), get("x").flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, width)


def _sums(patches: DataFrame, width: int, classes: int, schedule: tuple[float, ...], seed: int) -> list[tuple[np.ndarray, np.ndarray, float]]:
    """For each noise step the sums D'D, D'Y and Y'Y over all patches: a matrix a task, added up entry by entry."""
    side = width + classes + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((len(schedule) - 1, side * side + side * width + 1))
        for b in batches:
            if not b.num_rows:
                continue
            keys, label, x = _arrays(b, width)
            for t, a in enumerate(schedule[1:], 1):
                d = _design(np.sqrt(a) * x + np.sqrt(1 - a) * _normal(keys, t, seed, width), label, classes)
                total[t - 1] += np.concatenate([(d.T @ d).ravel(), (d.T @ x).ravel(), [(x * x).sum()]])
        flat = total.ravel()
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat), dtype=np.int32)), pa.array(flat)], names=["at", "v"])

    rows = patches.select("key", "label", "x").mapInArrow(run, "at int, v double").groupBy("at").agg(F.sum("v").alias("v")).collect()  # a row an entry
    flat = np.zeros((len(schedule) - 1) * (side * side + side * width + 1))
    for r in rows:
        flat[r["at"]] = r["v"]
    out = []
    for t in flat.reshape(len(schedule) - 1, -1):
        out.append((t[: side * side].reshape(side, side), t[side * side : -1].reshape(side, width), float(t[-1])))
    return out


def fit_denoiser(patches: DataFrame, width: int, classes: int, ridge: float = 1e-2, schedule: tuple[float, ...] = SCHEDULE, seed: int = 0) -> Denoiser:
    """Least squares with a ridge for each noise step from rows (key, label below `classes`, x of `width` numbers)."""
    solved = [np.linalg.solve(dd + ridge * np.eye(len(dd)), dy) for dd, dy, _ in _sums(patches, width, classes, schedule, seed)]
    return Denoiser(tuple(solved), classes, schedule)


def fit_adapter(base: Denoiser, patches: DataFrame, rank: int, ridge: float = 1e-2, seed: int = 1) -> tuple[Denoiser, list[float]]:
    """The frozen base with a correction of the given rank, fitted to other patches; also the squared error left at each step.

    The full correction is projected on the directions in which its fitted values vary
    most, so the error never rises with the rank.
    """
    width = base.matrices[0].shape[1]
    factors, errors = [], []
    for w, (dd, dy, yy) in zip(base.matrices, _sums(patches, width, base.classes, base.schedule, seed), strict=True):
        rest = dy - dd @ w
        full = np.linalg.solve(dd + ridge * np.eye(len(dd)), rest)
        _, vectors = np.linalg.eigh(full.T @ (dd + ridge * np.eye(len(dd))) @ full)
        top = vectors[:, ::-1][:, :rank]
        factors.append((full @ top, top.T))
        change = full @ top @ top.T
        m = w + change
        errors.append(float(yy - 2 * (m * dy).sum() + (m * (dd @ m)).sum()))
    return Denoiser(base.matrices, base.classes, base.schedule, tuple(factors)), errors


def _walk(model: Denoiser, x: np.ndarray, label: np.ndarray, begin: int, given: np.ndarray | None, real: np.ndarray | None, keys: list, seed: int) -> np.ndarray:
    """From noise step `begin` down to a clean patch; given cells are put back at the noise of each step."""
    for t in range(begin, 0, -1):
        a, b = model.schedule[t], model.schedule[t - 1]
        clean = model.clean(x, label, t)
        e = (x - np.sqrt(a) * clean) / np.sqrt(1 - a)
        x = np.sqrt(b) * clean + np.sqrt(1 - b) * e
        if given is not None:
            x = np.where(given, np.sqrt(b) * real + np.sqrt(1 - b) * _normal(keys, t - 1, seed, x.shape[1]), x)
    return x


def _made(df: DataFrame, width: int, make) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            get = lambda n: b.column(b.schema.get_field_index(n))  # noqa: E731, B023
            keys, label = get("key").to_pylist(), get("label").to_numpy(zero_copy_only=False).astype(np.int64)
            x = make(keys, label, get("x").flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, width) if "x" in b.schema.names else None)
            at = pa.array(np.arange(len(x) + 1, dtype=np.int32) * width)
            yield pa.RecordBatch.from_arrays([get("key"), get("label"), pa.ListArray.from_arrays(at, pa.array(x.ravel()))], names=["key", "label", "x"])

    kinds = dict(df.dtypes)
    return df.mapInArrow(run, f"key {kinds['key']}, label {kinds['label']}, x array<double>")


def text_to_image(model: Denoiser, wanted: DataFrame, seed: int = 0) -> DataFrame:
    """Patches of the wanted classes (key, label) from noise alone; the same key and seed give the same patch."""
    width, last = model.matrices[0].shape[1], len(model.schedule) - 1
    return _made(wanted.select("key", "label"), width, lambda keys, label, _: _walk(model, _normal(keys, last, seed, width), label, last, None, None, keys, seed))


def variant(model: Denoiser, patches: DataFrame, strength: float, seed: int = 0) -> DataFrame:
    """Variants of real patches (key, label, x) towards their label: noised up to a share of the steps and brought back; strength 0 gives the patch itself."""
    width, begin = model.matrices[0].shape[1], round(strength * (len(model.schedule) - 1))

    def make(keys: list, label: np.ndarray, x: np.ndarray) -> np.ndarray:
        a = model.schedule[begin]
        return _walk(model, np.sqrt(a) * x + np.sqrt(1 - a) * _normal(keys, begin, seed, width), label, begin, None, None, keys, seed) if begin else x

    return _made(patches.select("key", "label", "x"), width, make)


def inpaint(model: Denoiser, patches: DataFrame, given: np.ndarray, seed: int = 0) -> DataFrame:
    """Patches whose cells outside `given` are made anew around the given ones, which stay as they are; with the middle given this is outpainting."""
    width, last = model.matrices[0].shape[1], len(model.schedule) - 1
    return _made(patches.select("key", "label", "x"), width, lambda keys, label, x: _walk(model, np.where(given, np.sqrt(model.schedule[last]) * x, 0) + np.sqrt(1 - model.schedule[last]) * _normal(keys, last, seed, width), label, last, given, x, keys, seed))


def nearest_real(wanted: DataFrame, real: DataFrame) -> DataFrame:
    """Baseline: for each wanted (key, label) the real patch of the class that is nearest to the class's mean."""
    at = real.select("label", "key", "x", F.posexplode("x").alias("p", "v"))
    mean = at.groupBy("label", "p").agg(F.avg("v").alias("m"))
    far = at.select("label", "key", "p", "v").join(mean, ["label", "p"]).groupBy("label", "key").agg(F.sum((F.col("v") - F.col("m")) * (F.col("v") - F.col("m"))).alias("d"))
    best = far.groupBy("label").agg(F.min(F.struct("d", "key")).alias("b")).select("label", F.col("b.key").alias("real"))
    chosen = best.join(real.select(F.col("key").alias("real"), "x"), "real").select("label", "real", "x")
    return wanted.select("key", "label").join(F.broadcast(chosen), "label")  # a row a class


def quality(made: DataFrame, real: DataFrame) -> DataFrame:
    """Per class: distance of the means and of the standard deviations of generated and real patches, over all cells."""
    def moments(df: DataFrame, tag: str) -> DataFrame:
        e = df.select("label", F.posexplode("x").alias("p", "v"))
        return e.groupBy("label", "p").agg(F.avg("v").alias(f"m_{tag}"), F.stddev_pop("v").alias(f"s_{tag}"))

    j = moments(made, "a").join(moments(real, "b"), ["label", "p"])
    far = lambda k: F.sqrt(F.sum((F.col(f"{k}_a") - F.col(f"{k}_b")) * (F.col(f"{k}_a") - F.col(f"{k}_b"))))
    return j.groupBy("label").agg(far("m").alias("mean_distance"), far("s").alias("spread_distance"))


def qa_records(df: DataFrame, category: str, place: str) -> DataFrame:
    """Question and answer records as JSON from labels: how many samples of a category a place has, and which category is the most common."""
    n = df.groupBy(place, category).agg(F.count("*").alias("n"))
    count = n.select(F.col(place).alias("place"), F.lit("count").alias("kind"), F.to_json(F.struct(F.concat(F.lit("How many "), category, F.lit(" samples are there in "), F.col(place).cast("string"), F.lit("?")).alias("question"), F.col("n").cast("string").alias("answer"))).alias("record"))
    order = Window.partitionBy(place).orderBy(F.desc("n"), category)
    top = n.withColumn("r", F.row_number().over(order)).filter("r = 1")
    most = top.select(F.col(place).alias("place"), F.lit("most").alias("kind"), F.to_json(F.struct(F.concat(F.lit("Which category is the most common in "), F.col(place).cast("string"), F.lit("?")).alias("question"), F.col(category).alias("answer"))).alias("record"))
    return count.unionByName(most)
