"""The build of a corpus, end to end: select, resample, tile, pair, align, caption, label, split.

`build` runs it in miniature on the stand-in views and returns the release table.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from radarlake.methods import align, caption, release, spectrum, tiling
from radarlake.standins import captions, optical_tiles, scene_cells, scenes


@dataclass(frozen=True)
class Spec:
    """Parameters of a build."""

    target_m: float = spectrum.TARGET_M
    size: int = 8
    stride: int = 4
    min_valid: float = 0.5
    tile_pixels: int = 8
    max_rms: float = 0.5
    min_inside: float = 0.5
    strategy: str = "auto"


def corners(size: int, tile_pixels: int) -> list[align.Point]:
    """Corners of a patch and their place in its optical tile: a stand-in map, turned and shrunk by the patch's number."""
    last, end = float(size - 1), tile_pixels - 1.0
    turn = (F.col("tile_r") % 3) * 0.1
    shrink = 1 - (F.col("tile_c") % 2) * 0.05

    def place(x: float, y: float) -> tuple[Column, Column]:
        a, b = x / last - 0.5, y / last - 0.5
        return (0.5 + shrink * (F.lit(a) - turn * b)) * end, (0.5 + shrink * (F.lit(b) + turn * a)) * end

    return [(F.lit(x), F.lit(y), *place(x, y)) for x in (0.0, last) for y in (0.0, last)]


def patches(spark: SparkSession, sf_dir: str, spec: Spec = Spec()) -> DataFrame:
    """Patches of the resampled event scenes that are valid enough, with their maps."""
    sizes = scenes(spark)
    planned = spectrum.plan(sizes, spec.target_m).select("scene_id", "m_rows", "m_cols", "direction", "eff_az_m", "eff_rg_m")
    image = spectrum.resample(scene_cells(spark, sf_dir), sizes, spec.target_m, spec.strategy)
    tiles = tiling.explode_cells(image.join(planned, "scene_id"), spec.size, spec.stride, F.col("m_rows"), F.col("m_cols"))
    kept = tiling.select(tiles, spec.size, spec.min_valid)
    points = corners(spec.size, spec.tile_pixels)
    mapped = kept.join(planned, "scene_id").withColumn("map", align.fit(points))
    rms, _ = align.residuals(F.col("map"), points)
    return mapped.withColumn("rms", rms).withColumn("key", release.key("scene_id", "tile_r", "tile_c"))


def build(spark: SparkSession, sf_dir: str, spec: Spec = Spec()) -> DataFrame:
    """The release table: a row per sample with geometry, alignment, captions, category and split."""
    tiles = optical_tiles(spark, sf_dir).filter("band = 0")
    count = tiles.agg(F.count_distinct("tile_id").alias("tiles"))
    samples = patches(spark, sf_dir, spec).crossJoin(F.broadcast(count))
    number = F.col("tile_r") * 31 + F.col("tile_c")
    samples = samples.withColumn("tile_id", number % F.col("tiles")).drop("tiles")
    warped = align.warp_join(align.map_pixels(samples.select("key", "tile_id", "map", "rms"), spec.size), tiles, ["key"], spec.tile_pixels, spec.tile_pixels)
    seen = warped.groupBy("key").agg(F.avg(F.col("inside").cast("int")).alias("inside"), F.avg("value").alias("optical_mean"))
    texts = captions(spark, sf_dir).groupBy("sample_id").pivot("variant", ["SHORT", "MID", "LONG"]).agg(F.first("text"))
    docs = texts.agg((F.max("sample_id") + 1).alias("docs"))
    named = samples.join(seen, "key").crossJoin(F.broadcast(docs)).withColumn("sample_id", number % F.col("docs")).drop("docs")
    full = named.join(texts, "sample_id", "left")
    for v in ("SHORT", "MID", "LONG"):
        full = full.withColumn(v.lower(), caption.clean(F.col(v)))
    labelled = caption.label(full, text="mid")
    valid = (F.col("rms") <= spec.max_rms) & (F.col("inside") >= spec.min_inside)
    return release.split(labelled.withColumn("aligned", valid), "scene_id").select(
        "key", "scene_id", "tile_r", "tile_c", "direction", "eff_az_m", "eff_rg_m", "valid", "amplitude", "map", "rms", "inside", "aligned", "optical_mean", "tile_id", "short", "mid", "long", "category", "split"
    )
