"""Optical tiles for patches: web-mercator cover, distinct requests, the closest date, pixels of a mosaic."""

from __future__ import annotations

import math
from typing import Protocol

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

ZOOM = 19
#: Latitude where the square web map ends, and metres per pixel at zoom 0 on the equator.
MAX_LAT, METRES_PER_PIXEL = 85.05112878, 156543.03392804097


def world_x(lon: Column, zoom: int) -> Column:
    return (lon + 180e0) / 360e0 * float(1 << zoom)


def world_y(lat: Column, zoom: int) -> Column:
    p = F.radians(F.greatest(F.least(lat, F.lit(MAX_LAT)), F.lit(-MAX_LAT)))
    return (1e0 - F.ln(F.tan(p) + 1e0 / F.cos(p)) / math.pi) / 2e0 * float(1 << zoom)


def tile_x(lon: Column, zoom: int) -> Column:
    return F.pmod(F.floor(world_x(lon, zoom)), F.lit(1 << zoom))


def tile_y(lat: Column, zoom: int) -> Column:
    return F.greatest(F.lit(0), F.least(F.floor(world_y(lat, zoom)), F.lit((1 << zoom) - 1))).cast("long")


def tile_cover(df: DataFrame, zoom: int = ZOOM) -> DataFrame:
    """A row per tile that a box (south, north, west, east; west > east crosses 180 degrees) touches."""
    last = F.lit((1 << zoom) - 1).cast("long")
    x0, x1 = tile_x(F.col("west"), zoom), tile_x(F.col("east"), zoom)
    xs = F.when(x0 <= x1, F.sequence(x0, x1)).otherwise(F.concat(F.sequence(x0, last), F.sequence(F.lit(0).cast("long"), x1)))
    one = df.select("*", F.lit(zoom).alias("z"), F.explode(xs).alias("x"))
    return one.select("*", F.explode(F.sequence(tile_y(F.col("north"), zoom), tile_y(F.col("south"), zoom))).alias("y"))


def requests(cover: DataFrame) -> DataFrame:
    """Each tile once, with the number of patches that ask for it."""
    return cover.groupBy("z", "x", "y").agg(F.count("*").alias("patches"))


class TileSource(Protocol):
    """Anything that serves tiles of a catalogue: rows (z, x, y, dated, ...)."""

    def tiles(self, wanted: DataFrame) -> DataFrame: ...


class CatalogueSource:
    """Tiles of a catalogue table."""

    def __init__(self, table: DataFrame):
        self.table = table

    def tiles(self, wanted: DataFrame) -> DataFrame:
        return self.table.join(wanted.select("z", "x", "y"), ["z", "x", "y"], "left_semi")


def closest_date(patches: DataFrame, tiles: DataFrame, key: str, date: str, dated: str, keep: str) -> DataFrame:
    """For each patch the candidate tile of its place with the nearest date; of two as near, the earlier, then the smaller id."""
    gap = F.abs(F.datediff(F.col(dated), F.col(date)))
    j = patches.join(tiles, ["z", "x", "y"])
    return j.groupBy(key).agg(F.min(F.struct(gap.alias("gap"), F.col(dated).alias("dated"), F.col(keep).alias(keep))).alias("b")).select(key, "b.gap", "b.dated", f"b.{keep}")


def closest_other(df: DataFrame, place: list[str], key: str, date: str, keep: str) -> DataFrame:
    """For each row the other row of its place with the nearest date, ties as in `closest_date`, rows without a date last: (key, gap, keep).

    No pairs are made: of each day two rows can be wanted, and of the days beside it the first row. Only keys that
    occur more than once, whose own rows these may be, meet all rows of their places.
    """
    of = df.filter(F.col(key).isNotNull()).select(*place, F.to_date(date).alias("day"), F.col(date).alias("dated"), F.col(key).alias("id"))
    two = of.withColumn("r", F.row_number().over(Window.partitionBy(*place, "day").orderBy("dated", "id"))).filter("r <= 2")
    days = two.groupBy(*place, "day").agg(F.min(F.when(F.col("r") == 1, F.col("id"))).alias("first"), F.min(F.when(F.col("r") == 2, F.col("id"))).alias("second"))
    by = Window.partitionBy(*place).orderBy(F.asc_nulls_last("day"))
    beside = {"before": F.lag("first").over(by), "day_before": F.lag("day").over(by), "after": F.lead("first").over(by), "day_after": F.lead("day").over(by), "oldest": F.first("first").over(by)}
    near = days.withColumns(beside).withColumnRenamed("day", "of_day")
    j = of.select(*place, "id", "day").join(near, [*(of[c] == near[c] for c in place), of["day"].eqNullSafe(near["of_day"])])
    own = F.when(F.col("first") != F.col("id"), F.col("first")).otherwise(F.col("second"))
    back, on = F.datediff("day", "day_before"), F.datediff("day_after", "day")
    earlier = F.col("before").isNotNull() & (F.col("day_after").isNull() | (back <= on))
    dated = F.when(own.isNotNull(), F.struct(F.lit(0).alias("gap"), own.alias("other"))).when(earlier, F.struct(back.alias("gap"), F.col("before").alias("other"))).otherwise(F.struct(on.alias("gap"), F.col("after").alias("other")))
    undated = F.struct(F.lit(None).cast("int").alias("gap"), F.when(F.col("before").isNotNull(), F.col("oldest")).otherwise(own).alias("other"))
    found = j.select("id", F.when(F.col("day").isNull(), undated).otherwise(dated).alias("b"))
    many = of.groupBy("id").count().filter("count > 1").select("id")
    rest = of.join(many, "id").join(of.select(*place, F.col("day").alias("day2"), F.col("dated").alias("dated2"), F.col("id").alias("other")), place).filter("id <> other")
    gap = F.abs(F.datediff("day2", "day"))
    least = rest.groupBy("id").agg(F.min(F.struct(gap.isNull().alias("no_gap"), gap.alias("gap"), F.col("dated2").isNull().alias("no_date"), F.col("dated2"), F.col("other"))).alias("b"))
    both = found.join(many, "id", "left_anti").unionByName(least.select("id", F.struct("b.gap", "b.other").alias("b")))
    return both.filter("b.other is not null").select(F.col("id").alias(key), "b.gap", F.col("b.other").alias(keep))


def llh_to_px(lat: Column, lon: Column, x_min: Column, y_min: Column, zoom: int, pixels: int = 256) -> tuple[Column, Column]:
    """(u, v) in a mosaic whose upper left tile is (x_min, y_min); whole numbers are pixel centres."""
    return (world_x(lon, zoom) - x_min) * pixels - 0.5, (world_y(lat, zoom) - y_min) * pixels - 0.5


def gsd(lat: Column, zoom: int = ZOOM) -> Column:
    """Metres of ground per pixel."""
    return METRES_PER_PIXEL * F.cos(F.radians(lat)) / float(1 << zoom)


def mosaic(cover: DataFrame, pixels: DataFrame, key: str, size: int = 256) -> DataFrame:
    """Pixels (z, x, y, v, u, value) of each patch's tiles on one raster. They are many for their source's size, so they are never broadcast."""
    first = cover.groupBy(key).agg(F.min("x").alias("x_min"), F.min("y").alias("y_min"))
    j = cover.join(pixels.hint("merge"), ["z", "x", "y"]).join(first, key)
    return j.select(key, ((F.col("y") - F.col("y_min")) * size + F.col("v")).alias("v"), ((F.col("x") - F.col("x_min")) * size + F.col("u")).alias("u"), "value")
