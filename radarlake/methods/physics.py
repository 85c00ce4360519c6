"""Analyses of the complex signal: representations, looks, log-cumulants, despeckling."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F



def intensity() -> Column:
    return F.col("re") * F.col("re") + F.col("im") * F.col("im")


def represent(kind: str) -> Column:
    """`amplitude`, `intensity`, `db` (null at zero), `phase`, `phasor_re`, `phasor_im` of a cell."""
    i = intensity()
    a = F.sqrt(i)
    return {"amplitude": a, "intensity": i, "db": F.when(i > 0, 10 * F.log10(i)), "phase": F.atan2("im", "re"), "phasor_re": F.try_divide(F.col("re"), a), "phasor_im": F.try_divide(F.col("im"), a)}[kind]


def enl(cells: DataFrame, keys: list[str]) -> DataFrame:
    """Equivalent number of looks: squared mean over variance of the intensity."""
    i = cells.withColumn("i", intensity()).groupBy(*keys).agg(F.avg("i").alias("m"), F.var_samp("i").alias("v"))
    return i.select(*keys, F.try_divide(F.col("m") * F.col("m"), F.col("v")).alias("enl"))


def log_cumulants(cells: DataFrame, keys: list[str]) -> DataFrame:
    """Mean, variance and third central moment of ln intensity in one pass; zero intensities stay out."""
    y = cells.withColumn("i", intensity()).filter("i > 0").withColumn("y", F.ln("i"))
    g = y.groupBy(*keys).agg(F.count("*").alias("n"), F.avg("y").alias("k1"), F.var_pop("y").alias("k2"), F.skewness("y").alias("s"))
    return g.select(*keys, "n", "k1", "k2", (F.col("s") * F.pow("k2", F.lit(1.5))).alias("k3"))


def _neighbours(cells: DataFrame, half: int) -> DataFrame:
    """Mean and variance of the intensity around each present cell: cells go to their neighbours' places, no join of ranges."""
    steps = F.array(*(F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")) for a in range(-half, half + 1) for b in range(-half, half + 1)))
    sent = cells.select("scene_id", "r", "c", intensity().alias("i")).select("scene_id", "r", "c", "i", F.explode(steps).alias("s"))
    here = (F.col("s.a") == 0) & (F.col("s.b") == 0)
    at = sent.groupBy("scene_id", (F.col("r") + F.col("s.a")).alias("r"), (F.col("c") + F.col("s.b")).alias("c"))
    return at.agg(F.avg("i").alias("mean"), F.var_pop("i").alias("var"), F.max(F.when(here, F.col("i"))).alias("i")).filter("i is not null")


def multilook(cells: DataFrame, half: int) -> DataFrame:
    """Box mean of the intensity over (2 half + 1) squared cells."""
    return _neighbours(cells, half)


def lee(cells: DataFrame, half: int, looks: float) -> DataFrame:
    """Local linear filter: the weight of a cell falls as its neighbourhood looks like speckle of that many looks."""
    n = _neighbours(cells, half)
    w = F.greatest(F.lit(0.0), 1 - F.col("mean") * F.col("mean") / looks / F.col("var"))
    return n.withColumn("filtered", F.when(F.col("var") == 0, F.col("mean")).otherwise(F.col("mean") + w * (F.col("i") - F.col("mean"))))


def subapertures(cells: DataFrame, scenes: DataFrame, parts: int = 3, axis: int = 0) -> DataFrame:
    """Images (scene_id, part, r, c, re, im) of neighbouring parts of an axis' centred spectrum; they add up to the image, and so do their energies."""
    import numpy as np
    import pyarrow as pa

    def run(t: pa.Table) -> pa.Table:
        n, m = t["n_rows"][0].as_py(), t["n_cols"][0].as_py()
        x = np.zeros((n, m), complex)
        x[t["r"].to_numpy(), t["c"].to_numpy()] = t["re"].to_numpy() + 1j * t["im"].to_numpy()
        spectrum = np.fft.fftshift(np.fft.fft(x, axis=axis), axes=axis)
        out = []
        for k, bins in enumerate(np.array_split(np.arange(x.shape[axis]), parts)):
            kept = np.zeros_like(spectrum)
            at = (bins, slice(None)) if axis == 0 else (slice(None), bins)
            kept[at] = spectrum[at]
            y = np.fft.ifft(np.fft.ifftshift(kept, axes=axis), axis=axis)
            i, j = np.divmod(np.arange(y.size), m)
            out.append(pa.table({"scene_id": pa.array([t["scene_id"][0].as_py()] * y.size, t["scene_id"].type), "part": np.full(y.size, k, np.int32), "r": i.astype(np.int32), "c": j.astype(np.int32), "re": y.real.reshape(-1), "im": y.imag.reshape(-1)}))
        return pa.concat_tables(out)

    kind = dict(cells.dtypes)["scene_id"]
    joined = cells.join(scenes.select("scene_id", "n_rows", "n_cols"), "scene_id")
    return joined.groupBy("scene_id").applyInArrow(run, f"scene_id {kind}, part int, r int, c int, re double, im double")


def diversity(parts: DataFrame) -> DataFrame:
    """Variation of the amplitude over the sub-apertures of each cell, averaged by scene."""
    a = parts.withColumn("a", F.sqrt(intensity())).groupBy("scene_id", "r", "c").agg(F.try_divide(F.stddev_pop("a"), F.avg("a")).alias("cv"))
    return a.groupBy("scene_id").agg(F.avg("cv").alias("cv"))


def separability(cells: DataFrame, label: str, kinds: tuple[str, ...] = ("amplitude", "intensity", "db", "phase")) -> DataFrame:
    """For each representation the variance between the means of the classes over the variance within them."""
    wide = cells.select(label, F.explode(F.create_map(*(x for k in kinds for x in (F.lit(k), represent(k))))).alias("kind", "x")).filter("x is not null")
    by = wide.groupBy("kind", label).agg(F.count("*").alias("n"), F.avg("x").alias("m"), F.var_pop("x").alias("v"))
    total = by.groupBy("kind").agg((F.sum(F.col("n") * F.col("m")) / F.sum("n")).alias("mean"))
    j = by.join(F.broadcast(total), "kind")  # a row a representation
    between = F.sum(F.col("n") * (F.col("m") - F.col("mean")) * (F.col("m") - F.col("mean")))
    return j.groupBy("kind").agg(F.try_divide(between, F.sum(F.col("n") * F.col("v"))).alias("separability"))


def colorize(parts: DataFrame) -> DataFrame:
    """Amplitudes of three sub-apertures as red, green and blue, 0 to 255 of the scene's largest."""
    a = parts.withColumn("a", F.sqrt(intensity()))
    wide = a.groupBy("scene_id", "r", "c").pivot("part", [0, 1, 2]).agg(F.first("a")).toDF("scene_id", "r", "c", "a0", "a1", "a2")
    top = wide.groupBy("scene_id").agg(F.max(F.greatest("a0", "a1", "a2")).alias("top"))
    grey = lambda k: F.floor(F.coalesce(F.try_divide(k, "top"), F.lit(0.0)) * 255 + 0.5).cast("int")
    return wide.join(top, "scene_id").select("scene_id", "r", "c", grey("a0").alias("red"), grey("a1").alias("green"), grey("a2").alias("blue"))


def superres_pairs(cells: DataFrame, scenes: DataFrame, factor: int = 2) -> tuple[DataFrame, DataFrame]:
    """(low, full): images with the central 1 / factor of the azimuth spectrum alone, and the images they come from."""
    from radarlake.methods import spectrum

    sizes = scenes.withColumn("native_az_m", F.lit(spectrum.TARGET_M / factor)).withColumn("native_rg_m", F.lit(spectrum.TARGET_M))
    return spectrum.resample(cells, sizes), cells


def superres_zeropad(low: DataFrame, scenes: DataFrame, factor: int = 2) -> DataFrame:
    """Baseline: the low image brought back to its first size by zero-padding the spectrum."""
    from radarlake.methods import spectrum

    n = F.greatest(F.lit(1), F.floor(F.col("n_rows") / factor + 0.5).cast("int"))
    sizes = scenes.withColumn("native_az_m", spectrum.TARGET_M * F.col("n_rows") / n).withColumn("n_rows", n).withColumn("native_rg_m", F.lit(spectrum.TARGET_M))
    return spectrum.resample(low, sizes)


def homogeneity(cells: DataFrame, size: int, looks: float = 1.0, slack: float = 0.25) -> DataFrame:
    """Tiles whose intensity varies as speckle of that many looks does, or more: `homogeneous` or `scatterer`."""
    t = cells.withColumn("i", intensity()).groupBy("scene_id", F.floor(F.col("r") / size).cast("int").alias("tr"), F.floor(F.col("c") / size).cast("int").alias("tc"))
    cv = t.agg(F.count("*").alias("n"), F.try_divide(F.stddev_pop("i"), F.avg("i")).alias("cv"))
    return cv.withColumn("kind", F.when(F.col("cv") <= (1 + slack) / looks**0.5, "homogeneous").otherwise("scatterer"))


def by_incidence(df: DataFrame, angle: str, value: str, width: int = 10) -> DataFrame:
    """Mean and variance of a value in bins of the incidence angle."""
    return df.groupBy((F.floor(F.col(angle) / width) * width).cast("int").alias("from_deg")).agg(F.count("*").alias("n"), F.avg(value).alias("mean"), F.var_samp(value).alias("variance"))


def incidence_slope(df: DataFrame, angle: str, value: str) -> DataFrame:
    """Slope, intercept and fit of a value over the angle."""
    y, x = F.col(value), F.col(angle)
    return df.agg(F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"))


def disagreement(df: DataFrame, optical: str, radar: str) -> DataFrame:
    """How often each category of the caption meets each class of the radar signal, with the share of its category."""
    from pyspark.sql import Window

    n = df.groupBy(optical, radar).agg(F.count("*").alias("n"))
    return n.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy(optical)))


def masks(cells: DataFrame, share: float = 0.25, run: int = 2) -> DataFrame:
    """Cells in shadow: at least `run` neighbours in range below a share of the scene's mean intensity. Gaps between columns end a run."""
    from pyspark.sql import Window

    i = cells.select("scene_id", "r", "c", intensity().alias("i"))
    mean = i.groupBy("scene_id").agg(F.avg("i").alias("m"))
    low = i.join(mean, "scene_id").filter(F.col("i") < share * F.col("m"))
    # neighbouring low cells have one difference between column and rank
    line = Window.partitionBy("scene_id", "r")
    runs = low.withColumn("g", F.col("c") - F.row_number().over(line.orderBy("c")))
    return runs.withColumn("length", F.count("*").over(Window.partitionBy("scene_id", "r", "g")).cast("int")).filter(F.col("length") >= run).select("scene_id", "r", "c", "length")


def coarse_detected(cells: DataFrame, k: int) -> DataFrame:
    """Baseline of a coarse product: intensity in means of k by k cells, without phase."""
    t = cells.groupBy("scene_id", F.floor(F.col("r") / k).cast("int").alias("r"), F.floor(F.col("c") / k).cast("int").alias("c"))
    return t.agg(F.avg(intensity()).alias("intensity"), F.count("*").alias("looks"))


def coarse_loss(cells: DataFrame, k: int, spacing_m: float, incidence_deg: float) -> DataFrame:
    """What the coarse product loses: the share of the intensity's variation, and its ground spacing."""
    import math

    fine = cells.groupBy("scene_id").agg(F.sum(intensity() * intensity()).alias("e"))
    kept = coarse_detected(cells, k).groupBy("scene_id").agg(F.sum(F.col("looks") * F.col("intensity") * F.col("intensity")).alias("e2"))
    return fine.join(kept, "scene_id").select("scene_id", (1 - F.try_divide("e2", "e")).alias("lost"), F.lit(k * spacing_m / math.sin(math.radians(incidence_deg))).alias("ground_m"))
