"""Overlapping patches of images: where they start, which cells they hold, how they look."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def origins(extent: Column, size: int, stride: int, edge: str = "drop") -> Column:
    """Starts on one axis. `drop` leaves a rest at the edge, `shift` moves a last patch to the edge, `pad` lets it reach beyond."""
    last = extent - size
    whole = F.when(last >= 0, F.sequence(F.lit(0), F.floor(last / stride).cast("int"))).otherwise(F.array().cast("array<int>"))
    out = F.transform(whole, lambda k: (k * stride).cast("int"))
    if edge == "shift":
        return F.when(last > 0, F.array_distinct(F.concat(out, F.array(last.cast("int"))))).otherwise(out)
    if edge == "pad":
        count = F.ceil(F.greatest(F.lit(0), last) / stride).cast("int")
        return F.transform(F.sequence(F.lit(0), count), lambda k: (k * stride).cast("int"))
    return out


def index(df: DataFrame, size: int = 1024, stride: int = 512, edge: str = "drop", rows: str = "m_rows", cols: str = "m_cols") -> DataFrame:
    """A row per patch: its number along both axes and its origin."""
    r = df.select("*", F.posexplode(origins(F.col(rows), size, stride, edge)).alias("tile_r", "row0"))
    return r.select("*", F.posexplode(origins(F.col(cols), size, stride, edge)).alias("tile_c", "col0"))


def _holding(x: Column, extent: Column, size: int, stride: int) -> Column:
    count = F.floor((extent - size) / stride) + 1
    low = F.greatest(F.lit(0), F.ceil((x - size + 1) / F.lit(stride)))
    high = F.least(count - 1, F.floor(x / F.lit(stride)))
    return F.when(low <= high, F.sequence(low.cast("int"), high.cast("int"))).otherwise(F.array().cast("array<int>"))


def explode_cells(cells: DataFrame, size: int, stride: int, rows: Column, cols: Column) -> DataFrame:
    """Each cell in every patch that holds it, without a join: the patches are a range of numbers on each axis."""
    r = cells.select("*", F.explode(_holding(F.col("r"), rows, size, stride)).alias("tile_r"))
    both = r.select("*", F.explode(_holding(F.col("c"), cols, size, stride)).alias("tile_c"))
    return both.withColumn("y", F.col("r") - F.col("tile_r") * stride).withColumn("x", F.col("c") - F.col("tile_c") * stride)


def from_blocks(cells: DataFrame, stride: int, rows: Column, cols: Column) -> DataFrame:
    """Patches of twice the stride as views over blocks of one stride: a block goes to the up to four patches it is a quarter of."""
    size = 2 * stride
    block = cells.withColumn("br", F.floor(F.col("r") / stride).cast("int")).withColumn("bc", F.floor(F.col("c") / stride).cast("int"))
    packed = block.groupBy("scene_id", "br", "bc").agg(F.collect_list(F.struct("r", "c", "re", "im")).alias("cells"))
    quarter = lambda b, n: F.filter(F.array(F.col(b) - 1, F.col(b)), lambda t: (t >= 0) & (t * stride + size <= n))
    placed = packed.select("*", F.explode(quarter("br", rows)).alias("tile_r")).select("*", F.explode(quarter("bc", cols)).alias("tile_c"))
    out = placed.select("scene_id", "tile_r", "tile_c", F.explode("cells").alias("s")).select("scene_id", "tile_r", "tile_c", "s.*")
    return out.withColumn("y", F.col("r") - F.col("tile_r") * stride).withColumn("x", F.col("c") - F.col("tile_c") * stride)


def select(tiles: DataFrame, size: int, min_valid: float = 0.0, min_amplitude: float = 0.0, keys: tuple[str, ...] = ("scene_id", "tile_r", "tile_c")) -> DataFrame:
    """Patches by their share of cells that are present and by their mean amplitude."""
    a = tiles.groupBy(*keys).agg((F.count("*") / (size * size)).alias("valid"), F.avg(F.hypot("re", "im")).alias("amplitude"))
    return a.filter((F.col("valid") >= min_valid) & (F.col("amplitude") >= min_amplitude))


def amplitude() -> Column:
    return F.sqrt(F.col("re") * F.col("re") + F.col("im") * F.col("im"))


def preview(cells: DataFrame, how: str = "percentile", key: str = "scene_id", low: float = 0.01, high: float = 0.99, floor_db: float = -40.0) -> DataFrame:
    """8-bit amplitudes: `minmax`, `percentile`, or `db` below the largest."""
    a = cells.withColumn("a", amplitude())
    if how == "percentile":
        ends = a.groupBy(key).agg(F.percentile("a", F.lit(low)).alias("lo"), F.percentile("a", F.lit(high)).alias("hi"))
    else:
        ends = a.groupBy(key).agg(F.min("a").alias("lo"), F.max("a").alias("hi"))
    j = a.join(ends, key)
    if how == "db":
        x = (20 * F.log10(F.greatest(F.try_divide("a", "hi"), F.lit(1e-12))) - floor_db) / -floor_db
    else:
        x = F.coalesce(F.try_divide(F.col("a") - F.col("lo"), F.col("hi") - F.col("lo")), F.lit(0.0))
    return j.withColumn("grey", F.floor(F.greatest(F.lit(0.0), F.least(F.lit(1.0), x)) * 255 + 0.5 - 1e-9).cast("int")).drop("lo", "hi")


def series(df: DataFrame, time: str, size: str, stride: str) -> DataFrame:
    """Windows of a time series of the given size at each stride, with count and sum of `value`."""
    w = df.groupBy(F.window(time, size, stride)).agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return w.select(F.col("window.start").alias("start"), "n", "total")
