"""Resampling in the Fourier domain: crop or zero-pad the centred spectrum, axis by axis.

A complex image has n samples on an axis and gets m: its spectrum's k = min(n, m)
central bins stay (for even k the negative Nyquist bin), and amplitudes scale by m / n.
Three strategies give the same image: `local` transforms a scene in one task,
`separable` transforms rows where they lie and deals out columns once, `kernel` joins
with the axis kernels and stays in SQL. Absent cells are zero.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TARGET_M = 0.8
#: Bytes that one task may hold for a scene; above it `auto` takes the separable strategy.
TASK_BYTES = 512 << 20


def size(n: Column, native: Column, target: float = TARGET_M) -> Column:
    """Samples after resampling."""
    return F.greatest(F.lit(1), F.floor(n * native / F.lit(float(target)) + 0.5).cast("int"))


def direction(n: Column, m: Column) -> Column:
    return F.when(m < n, "down").when(m > n, "up").otherwise("identity")


def plan(df: DataFrame, target: float = TARGET_M) -> DataFrame:
    """Sizes, directions and effective spacings from n_rows, n_cols, native_az_m, native_rg_m."""
    out = df.withColumn("m_rows", size(F.col("n_rows"), F.col("native_az_m"), target)).withColumn("m_cols", size(F.col("n_cols"), F.col("native_rg_m"), target))
    out = out.withColumn("dir_az", direction(F.col("n_rows"), F.col("m_rows"))).withColumn("dir_rg", direction(F.col("n_cols"), F.col("m_cols")))
    out = out.withColumn("direction", F.when(F.col("dir_az") == F.col("dir_rg"), F.col("dir_az")).otherwise("mixed"))
    return out.withColumn("eff_az_m", F.col("n_rows") * F.col("native_az_m") / F.col("m_rows")).withColumn("eff_rg_m", F.col("n_cols") * F.col("native_rg_m") / F.col("m_cols"))


def provenance(df: DataFrame, target: float = TARGET_M) -> DataFrame:
    """What a release records of the resampling; upsampling adds samples and no detail."""
    p = plan(df, target)
    share = lambda n, m: F.least(F.lit(1.0), F.col(n) / F.col(m))
    return p.select("scene_id", "direction", "n_rows", "n_cols", "m_rows", "m_cols", "eff_az_m", "eff_rg_m", share("m_rows", "n_rows").alias("kept_az"), share("m_cols", "n_cols").alias("kept_rg"), share("n_rows", "m_rows").alias("bandwidth_az"), share("n_cols", "m_cols").alias("bandwidth_rg"))


def resample_axis(x: np.ndarray, m: int, axis: int) -> np.ndarray:
    """numpy: the centred crop or pad of one axis."""
    n = x.shape[axis]
    if m == n:
        return x
    k = min(n, m)
    spectrum = np.fft.fftshift(np.fft.fft(x, axis=axis), axes=axis)
    band = np.take(spectrum, range(n // 2 - k // 2, n // 2 - k // 2 + k), axis)
    around = [(0, 0)] * x.ndim
    around[axis] = (m // 2 - k // 2, m - k - (m // 2 - k // 2))
    return np.fft.ifft(np.fft.ifftshift(np.pad(band, around), axes=axis), axis=axis) * (m / n)


def _image(t: pa.Table, rows: int, cols: int, r: str = "r", c: str = "c") -> np.ndarray:
    x = np.zeros((rows, cols), complex)
    x[t[r].to_numpy(), t[c].to_numpy()] = t["re"].to_numpy() + 1j * t["im"].to_numpy()
    return x


def _cells(key: object, kind: pa.DataType, y: np.ndarray, row0: int = 0, col0: int = 0) -> pa.Table:
    i, j = np.divmod(np.arange(y.size), y.shape[1])
    return pa.table({"scene_id": pa.array([key] * y.size, kind), "r": (i + row0).astype(np.int32), "c": (j + col0).astype(np.int32), "re": y.real.reshape(-1), "im": y.imag.reshape(-1)})


def _local(cells: DataFrame, planned: DataFrame) -> DataFrame:
    def run(t: pa.Table) -> pa.Table:
        n, m, o, q = (t[k][0].as_py() for k in ("n_rows", "n_cols", "m_rows", "m_cols"))
        y = resample_axis(resample_axis(_image(t, n, m), o, 0), q, 1)
        return _cells(t["scene_id"][0].as_py(), t["scene_id"].type, y)

    kind = dict(cells.dtypes)["scene_id"]
    joined = cells.join(planned.select("scene_id", "n_rows", "n_cols", "m_rows", "m_cols"), "scene_id")
    return joined.groupBy("scene_id").applyInArrow(run, f"scene_id {kind}, r int, c int, re double, im double")


def _separable(cells: DataFrame, planned: DataFrame, block: int) -> DataFrame:
    """Each row on its own, then blocks of columns; a task holds a row, or a block of columns."""
    kind = dict(cells.dtypes)["scene_id"]
    sizes = planned.select("scene_id", "n_rows", "n_cols", "m_rows", "m_cols")

    def rows(t: pa.Table) -> pa.Table:
        y = resample_axis(_image(pa.table({**{k: t[k] for k in ("c", "re", "im")}, "z": np.zeros(len(t), np.int32)}), 1, t["n_cols"][0].as_py(), "z"), t["m_cols"][0].as_py(), 1)
        return _cells(t["scene_id"][0].as_py(), t["scene_id"].type, y, t["r"][0].as_py())

    def columns(t: pa.Table) -> pa.Table:
        first = t["b"][0].as_py() * block
        width = min(block, t["m_cols"][0].as_py() - first)
        shifted = pa.table({"r": t["r"], "c": t["c"].to_numpy() - first, "re": t["re"], "im": t["im"]})
        return _cells(t["scene_id"][0].as_py(), t["scene_id"].type, resample_axis(_image(shifted, t["n_rows"][0].as_py(), width), t["m_rows"][0].as_py(), 0), 0, first)

    schema = f"scene_id {kind}, r int, c int, re double, im double"
    wide = cells.join(sizes, "scene_id").groupBy("scene_id", "r").applyInArrow(rows, schema)
    dealt = wide.join(sizes, "scene_id").withColumn("b", F.floor(F.col("c") / block).cast("int"))
    return dealt.groupBy("scene_id", "b").applyInArrow(columns, schema)


def kernel(n: Column, m: Column, i: Column, j: Column) -> tuple[Column, Column]:
    """Real and imaginary part of the axis kernel from sample j of n to sample i of m: the sum over the kept bins in closed form."""
    k = F.least(n, m)
    x = i / m - j / n
    s = F.sin(F.lit(math.pi) * x)
    # x is a multiple of 1 only where both positions meet
    ratio = F.when(F.abs(s) < 1e-12, k.cast("double")).otherwise(F.sin(F.lit(math.pi) * k * x) / s)
    even = k % 2 == 0
    return F.when(even, F.cos(F.lit(math.pi) * x) * ratio).otherwise(ratio) / n, F.when(even, -F.sin(F.lit(math.pi) * x) * ratio).otherwise(F.lit(0.0)) / n


def _kernel_table(planned: DataFrame, n: str, m: str, to: str, at: str) -> DataFrame:
    t = planned.select("scene_id", n, m, F.explode(F.sequence(F.lit(0), F.col(m) - 1)).alias(to)).select("*", F.explode(F.sequence(F.lit(0), F.col(n) - 1)).alias(at))
    re, im = kernel(F.col(n), F.col(m), F.col(to), F.col(at))
    return t.select("scene_id", to, at, re.alias("k_re"), im.alias("k_im"))


def _product() -> tuple[Column, Column]:
    a, b, c, d = (F.col(x) for x in ("re", "im", "k_re", "k_im"))
    return F.sum(a * c - b * d).alias("re"), F.sum(a * d + b * c).alias("im")


def _kernel(cells: DataFrame, planned: DataFrame) -> DataFrame:
    rows = _kernel_table(planned, "n_rows", "m_rows", "i", "r")
    cols = _kernel_table(planned, "n_cols", "m_cols", "j", "c")
    half = cells.join(rows, ["scene_id", "r"]).groupBy("scene_id", "i", "c").agg(*_product())
    return half.join(cols, ["scene_id", "c"]).groupBy("scene_id", "i", "j").agg(*_product()).select("scene_id", F.col("i").alias("r"), F.col("j").alias("c"), "re", "im")


def resample(cells: DataFrame, scenes: DataFrame, target: float = TARGET_M, strategy: str = "auto", block: int = 512) -> DataFrame:
    """Images (scene_id, r, c, re, im) at the target spacing; scenes that have it already pass unchanged.

    `auto` decides scene by scene: `local` while a task can hold it, else `separable`.
    """
    planned = plan(scenes, target)
    if strategy == "kernel":
        return _kernel(cells, planned)
    cost = 3 * 16 * F.greatest("n_rows", "m_rows").cast("long") * F.greatest("n_cols", "m_cols")
    way = F.when(F.col("direction") == "identity", "same").otherwise(F.when(cost <= TASK_BYTES, "local").otherwise("separable") if strategy == "auto" else F.lit(strategy))
    ways = planned.withColumn("way", way)
    of = lambda w: ways.filter(F.col("way") == w)
    mine = lambda w: cells.join(of(w).select("scene_id"), "scene_id", "left_semi")
    out = mine("same").select("scene_id", "r", "c", "re", "im")
    if strategy in ("auto", "local"):
        out = out.unionByName(_local(mine("local"), of("local")))
    if strategy in ("auto", "separable"):
        out = out.unionByName(_separable(mine("separable"), of("separable"), block))
    return out


def dft(cells: DataFrame, scenes: DataFrame) -> DataFrame:
    """Centred spectrum (scene_id, fr, fc, re, im)."""

    def run(t: pa.Table) -> pa.Table:
        n, m = t["n_rows"][0].as_py(), t["n_cols"][0].as_py()
        return _cells(t["scene_id"][0].as_py(), t["scene_id"].type, np.fft.fftshift(np.fft.fft2(_image(t, n, m))), -(n // 2), -(m // 2)).rename_columns(["scene_id", "fr", "fc", "re", "im"])

    kind = dict(cells.dtypes)["scene_id"]
    return cells.join(scenes.select("scene_id", "n_rows", "n_cols"), "scene_id").groupBy("scene_id").applyInArrow(run, f"scene_id {kind}, fr int, fc int, re double, im double")


def resample_1d(df: DataFrame, n: int, m: int, at: str = "t", value: str = "x") -> DataFrame:
    """A real series of n points (rows of `key`, `at`, `value`; absent points are zero) as m points."""

    def run(t: pa.Table) -> pa.Table:
        x = np.zeros(n, complex)
        x[t[at].to_numpy()] = t[value].to_numpy()
        y = resample_axis(x, m, 0)
        return pa.table({"key": pa.array([t["key"][0].as_py()] * m, t["key"].type), "t": np.arange(m, dtype=np.int32), "x": y.real})

    return df.groupBy("key").applyInArrow(run, f"key {dict(df.dtypes)['key']}, t int, x double")


def _takers(method: str, n: Column, m: Column, at: Column) -> Column:
    """The output samples (to, w) of one axis that take from input sample `at`, from the sizes alone.

    Output i lies at a = i n / m of the input. The outputs near an input are a range of
    numbers, which is filtered by the very rule, so that no table of samples is needed.
    """
    last = n - 1
    low = F.greatest(F.lit(0), F.floor((at - 2) * m / n))
    # the last sample also stands for all places beyond it
    high = F.least(m - 1, F.when(at == last, m - 1).otherwise(F.ceil((at + 2) * m / n)))
    near = F.transform(F.sequence(low.cast("int"), high.cast("int")), lambda i: F.struct(i.alias("to"), (i * n / m).alias("a")))

    def weighed(s: Column) -> Column:
        a = s["a"]
        if method == "nearest":
            w = F.when(F.least(F.floor(a + 0.5), last) == at, 1.0)
        elif method == "bilinear":
            whole = F.floor(a)
            takes = (whole == at) | (F.least(whole + 1, last) == at)
            w = F.when(takes, F.when(whole == at, 1 - (a - whole)).otherwise(0.0) + F.when(F.least(whole + 1, last) == at, a - whole).otherwise(0.0))
        else:
            first, end = F.floor(a), F.least(F.greatest(F.floor(a), F.ceil((s["to"] + 1) * n / m) - 1), last)
            w = F.when((at >= first) & (at <= end), 1.0 / (end - first + 1))
        return F.struct(s["to"].alias("to"), w.alias("w"))

    wide = near
    if method == "box":
        # a box may be wider than two samples: it begins at most its width before the sample
        low = F.greatest(F.lit(0), F.floor(at * m / n) - 1)
        high = F.least(m - 1, F.ceil((at + 1) * m / n) + 1)
        wide = F.transform(F.sequence(low.cast("int"), high.cast("int")), lambda i: F.struct(i.alias("to"), (i * n / m).alias("a")))
    return F.filter(F.transform(wide, weighed), lambda s: s["w"].isNotNull())


def resample_spatial(cells: DataFrame, scenes: DataFrame, method: str, target: float = TARGET_M) -> DataFrame:
    """Baselines on pixels: `nearest`, `bilinear`, `box`, and `detected` (intensity in box means, no phase)."""
    sizes = plan(scenes, target).select("scene_id", "n_rows", "n_cols", "m_rows", "m_cols")
    if method == "detected":
        cells, method = cells.select("scene_id", "r", "c", (F.col("re") ** 2 + F.col("im") ** 2).alias("re"), F.lit(0.0).alias("im")), "box"
    placed = cells.join(sizes, "scene_id")
    one = placed.select("*", F.explode(_takers(method, F.col("n_rows"), F.col("m_rows"), F.col("r"))).alias("p"))
    both = one.select("*", F.explode(_takers(method, F.col("n_cols"), F.col("m_cols"), F.col("c"))).alias("q"))
    w = F.col("p.w") * F.col("q.w")
    return both.groupBy("scene_id", F.col("p.to").alias("r"), F.col("q.to").alias("c")).agg(F.sum(F.col("re") * w).alias("re"), F.sum(F.col("im") * w).alias("im"))


def energy(cells: DataFrame, resampled: DataFrame, scenes: DataFrame, target: float = TARGET_M) -> DataFrame:
    """Mean power per pixel before and after, and their ratio."""
    planned = plan(scenes, target)
    power = lambda d, name: d.groupBy("scene_id").agg(F.sum(F.col("re") ** 2 + F.col("im") ** 2).alias(name))
    j = planned.join(power(cells, "e_in"), "scene_id").join(power(resampled, "e_out"), "scene_id")
    before, after = F.col("e_in") / (F.col("n_rows") * F.col("n_cols")), F.col("e_out") / (F.col("m_rows") * F.col("m_cols"))
    return j.select("scene_id", "direction", before.alias("power_in"), after.alias("power_out"), F.try_divide(after, before).alias("ratio"))


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """Relative root mean square error of b against a, and their coherence, by scene; absent cells are zero."""
    y = b.select("scene_id", "r", "c", F.col("re").alias("re2"), F.col("im").alias("im2"))
    z = lambda c: F.coalesce(F.col(c), F.lit(0.0))
    j = a.join(y, ["scene_id", "r", "c"], "full").select("scene_id", *(z(c).alias(c) for c in ("re", "im", "re2", "im2")))
    pa_, pb = F.sum(F.col("re") ** 2 + F.col("im") ** 2), F.sum(F.col("re2") ** 2 + F.col("im2") ** 2)
    d = F.sum((F.col("re") - F.col("re2")) ** 2 + (F.col("im") - F.col("im2")) ** 2)
    dot_re, dot_im = F.sum(F.col("re") * F.col("re2") + F.col("im") * F.col("im2")), F.sum(F.col("im") * F.col("re2") - F.col("re") * F.col("im2"))
    return j.groupBy("scene_id").agg(F.sqrt(F.try_divide(d, pa_)).alias("rmse"), F.try_divide(F.hypot(dot_re, dot_im), F.sqrt(pa_ * pb)).alias("coherence"))
