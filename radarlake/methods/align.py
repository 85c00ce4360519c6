"""Affine maps between pixels of a patch and of an optical tile, and warping by them.

A map is a struct (a11, a12, tx, a21, a22, ty) that takes (x, y) = (column, row) of the
radar patch to (u, v) of the tile. Points of which no unique map follows give null.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from radarlake.methods.geo import bound

Point = tuple[Column, Column, Column, Column]  # x, y, u, v
FIELDS = ("a11", "a12", "tx", "a21", "a22", "ty")


def _solved(n: Column, sx: Column, sy: Column, su: Column, sv: Column, xx: Column, yy: Column, xy: Column, xu: Column, yu: Column, xv: Column, yv: Column) -> Column:
    """The map from centred sums (xx, ... about the means)."""
    d = xx * yy - xy * xy
    bad = F.abs(d) <= 1e-12 * (F.abs(xx * yy) + 1e-300)
    a11, a12 = (xu * yy - yu * xy) / d, (yu * xx - xu * xy) / d
    a21, a22 = (xv * yy - yv * xy) / d, (yv * xx - xv * xy) / d
    mx, my, mu, mv = sx / n, sy / n, su / n, sv / n
    values = (a11, a12, mu - a11 * mx - a12 * my, a21, a22, mv - a21 * mx - a22 * my)
    safe = F.struct(*(v.alias(k) for k, v in zip(FIELDS, values, strict=True)))
    return F.when(~bad, safe)


def fit(points: list[Point]) -> Column:
    """Least squares over three, four or more corners of a row; three are met exactly."""
    n = len(points)
    named = {f"{k}{i}": c for i, p in enumerate(points) for k, c in zip("xyuv", p, strict=True)}

    def centred(p: Column) -> Column:
        total = lambda f: sum((f(i) for i in range(1, n)), f(0))
        return bound({f"s{k}": total(lambda i, k=k: p[f"{k}{i}"]) for k in "xyuv"}, lambda s: products(p, s, total))

    def products(p: Column, s: Column, total) -> Column:
        about = lambda a, b: total(lambda i: (p[f"{a}{i}"] - s[f"s{a}"] / n) * (p[f"{b}{i}"] - s[f"s{b}"] / n))
        pairs = ("xx", "yy", "xy", "xu", "yu", "xv", "yv")
        return bound({k: about(*k) for k in pairs}, lambda q: _solved(F.lit(float(n)), *(s[f"s{k}"] for k in "xyuv"), *(q[k] for k in pairs)))

    return bound(named, centred)


def fit_points(df: DataFrame, keys: list[str], x: str = "x", y: str = "y", u: str = "u", v: str = "v") -> DataFrame:
    """Least squares over the rows of each key: one aggregate of covariances."""
    c = lambda a, b: F.covar_pop(a, b)
    sums = df.groupBy(*keys).agg(F.count("*").alias("n"), *(F.avg(k).alias(f"m{i}") for i, k in enumerate((x, y, u, v))), c(x, x).alias("xx"), c(y, y).alias("yy"), c(x, y).alias("xy"), c(x, u).alias("xu"), c(y, u).alias("yu"), c(x, v).alias("xv"), c(y, v).alias("yv"))
    one = F.lit(1.0)
    solved = _solved(one, *(F.col(k) for k in ("m0", "m1", "m2", "m3", "xx", "yy", "xy", "xu", "yu", "xv", "yv")))
    return sums.select(*keys, "n", solved.alias("map"))


def apply(a: Column, x: Column, y: Column) -> tuple[Column, Column]:
    return a["a11"] * x + a["a12"] * y + a["tx"], a["a21"] * x + a["a22"] * y + a["ty"]


def invert(a: Column) -> Column:
    """The map from the tile to the patch; null if there is none."""
    d = a["a11"] * a["a22"] - a["a12"] * a["a21"]
    b11, b12, b21, b22 = a["a22"] / d, -a["a12"] / d, -a["a21"] / d, a["a11"] / d
    values = (b11, b12, -(b11 * a["tx"] + b12 * a["ty"]), b21, b22, -(b21 * a["tx"] + b22 * a["ty"]))
    return F.when(F.abs(d) > 1e-12, F.struct(*(v.alias(k) for k, v in zip(FIELDS, values, strict=True))))


def residuals(a: Column, points: list[Point]) -> tuple[Column, Column]:
    """Root mean square and largest distance between mapped and given points."""
    squared = []
    for x, y, u, v in points:
        p, q = apply(a, x, y)
        squared.append((p - u) * (p - u) + (q - v) * (q - v))
    return F.sqrt(sum(squared[1:], squared[0]) / len(squared)), F.sqrt(F.greatest(*squared))


def map_pixels(df: DataFrame, size: int, a: str = "map") -> DataFrame:
    """Every output pixel (x, y) of a patch with its place (pu, pv) in the tile."""
    px = df.select("*", F.explode(F.sequence(F.lit(0), F.lit(size - 1))).alias("y")).select("*", F.explode(F.sequence(F.lit(0), F.lit(size - 1))).alias("x"))
    u, v = apply(F.col(a), F.col("x"), F.col("y"))
    return px.withColumn("pu", u).withColumn("pv", v)


def _inside(width: int, height: int, u: Column | None = None, v: Column | None = None) -> Column:
    u, v = F.col("pu") if u is None else u, F.col("pv") if v is None else v
    return u.between(0, width - 1) & v.between(0, height - 1)


def warp(mapped: DataFrame, image: str, width: int, height: int, method: str = "bilinear") -> DataFrame:
    """In-row sampling: `image` is an array of rows; pixels outside are 0 with `inside` false."""
    at = lambda v, u: F.element_at(F.element_at(F.col(image), (v + 1).cast("int")), (u + 1).cast("int"))
    inside = _inside(width, height)
    u, v = F.greatest(F.lit(0.0), F.least(F.col("pu"), F.lit(width - 1.0))), F.greatest(F.lit(0.0), F.least(F.col("pv"), F.lit(height - 1.0)))
    if method == "nearest":
        value = at(F.floor(v + 0.5), F.floor(u + 0.5))
    else:
        i, j = F.least(F.floor(u), F.lit(max(width - 2, 0))), F.least(F.floor(v), F.lit(max(height - 2, 0)))
        i1, j1 = F.least(i + 1, F.lit(width - 1)), F.least(j + 1, F.lit(height - 1))
        a, b = u - i, v - j
        value = (1 - a) * (1 - b) * at(j, i) + a * (1 - b) * at(j, i1) + (1 - a) * b * at(j1, i) + a * b * at(j1, i1)
    return mapped.withColumn("inside", inside).withColumn("value", F.when(inside, value).otherwise(0.0)).drop(image)


def warp_join(mapped: DataFrame, cells: DataFrame, keys: list[str], width: int, height: int, method: str = "bilinear") -> DataFrame:
    """The same over long images (tile_id, v, u, value): each inside pixel meets up to four cells and adds them up.

    Pixels are made from few rows, so that Spark takes them for small and would broadcast them; hence the hints.
    """
    if method == "nearest":
        near = F.array(F.struct(F.floor(F.col("pu") + 0.5).cast("int").alias("u"), F.floor(F.col("pv") + 0.5).cast("int").alias("v"), F.lit(1.0).alias("w")))
    else:
        i, j = F.least(F.floor("pu"), F.lit(width - 2)), F.least(F.floor("pv"), F.lit(height - 2))
        a, b = F.col("pu") - i, F.col("pv") - j
        corner = lambda di, dj, w: F.struct((i + di).cast("int").alias("u"), (j + dj).cast("int").alias("v"), w.alias("w"))
        near = F.array(corner(0, 0, (1 - a) * (1 - b)), corner(1, 0, a * (1 - b)), corner(0, 1, (1 - a) * b), corner(1, 1, a * b))
    some = mapped.withColumn("inside", _inside(width, height))
    spread = some.filter("inside").select(*keys, "x", "y", "tile_id", F.explode(near).alias("s")).select(*keys, "x", "y", "tile_id", "s.u", "s.v", "s.w")
    summed = spread.join(cells.select("tile_id", "u", "v", "value").hint("merge"), ["tile_id", "u", "v"]).groupBy(*keys, "x", "y").agg(F.sum(F.col("w") * F.col("value")).alias("value"))
    out = some.select(*keys, "x", "y", "inside").join(summed.hint("merge"), [*keys, "x", "y"], "left")
    return out.withColumn("value", F.coalesce("value", F.lit(0.0)))


def images(cells: DataFrame, width: int, height: int) -> DataFrame:
    """Long images (tile_id, v, u, value) as a row a tile with `image`, an array of rows; cells that occur again add up, absent ones are null."""
    n = width * height
    within = cells.filter(F.col("u").between(0, width - 1) & F.col("v").between(0, height - 1))
    summed = within.groupBy("tile_id", (F.col("v") * width + F.col("u")).cast("int").alias("p")).agg(F.sum("value").alias("value"))
    listed = summed.groupBy("tile_id").agg(F.sort_array(F.collect_list(F.struct("p", "value"))).alias("cells"))
    filled = bound({"m": F.map_from_entries("cells")}, lambda b: F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda p: F.try_element_at(b["m"], p)))
    flat = F.when(F.size("cells") == n, F.transform("cells", lambda s: s["value"])).otherwise(filled)
    rows = bound({"f": flat}, lambda b: F.transform(F.sequence(F.lit(0), F.lit(height - 1)), lambda v: F.slice(b["f"], v * width + 1, F.lit(width))))
    return listed.select("tile_id", rows.alias("image"))


def warp_rows(patches: DataFrame, size: int, width: int, height: int, image: str = "image", a: str = "map") -> DataFrame:
    """Bilinear warp inside a row: `image` gives way to `pixels`, an array of (x, y, inside, value) line by line.

    The values are those of `warp_join`, but pixels and their corners never become rows.
    """

    def pixels(b: Column) -> Column:
        at = F.transform(F.sequence(F.lit(0), F.lit(size * size - 1)), lambda p: F.struct((p % size).alias("x"), F.floor(p / size).cast("int").alias("y")))
        return F.transform(F.transform(F.transform(at, lambda s: placed(b["map"], s)), near), lambda s: valued(b["image"], s))

    def placed(m: Column, s: Column) -> Column:
        u, v = apply(m, s["x"], s["y"])
        return F.struct(s["x"].alias("x"), s["y"].alias("y"), u.alias("pu"), v.alias("pv"))

    def near(s: Column) -> Column:
        inside = _inside(width, height, s["pu"], s["pv"])
        corner = lambda k, n: F.when(inside, F.least(F.floor(s[k]), F.lit(n - 2))).cast("int")
        return F.struct(s["x"].alias("x"), s["y"].alias("y"), inside.alias("inside"), s["pu"].alias("pu"), s["pv"].alias("pv"), corner("pu", width).alias("i"), corner("pv", height).alias("j"))

    def valued(rows: Column, s: Column) -> Column:
        a, b = s["pu"] - s["i"], s["pv"] - s["j"]
        cell = lambda di, dj, w: F.coalesce(w * F.get(F.get(rows, s["j"] + dj), s["i"] + di), F.lit(0.0))
        total = cell(0, 0, (1 - a) * (1 - b)) + cell(1, 0, a * (1 - b)) + cell(0, 1, (1 - a) * b) + cell(1, 1, a * b)
        return F.struct(s["x"].alias("x"), s["y"].alias("y"), s["inside"].alias("inside"), F.when(s["inside"], total).otherwise(0.0).alias("value"))

    return patches.withColumn("pixels", bound({"map": F.col(a), "image": F.col(image)}, pixels)).drop(image)


def project_layer(patches: DataFrame, layer: DataFrame, keys: list[str], size: int, width: int, height: int, method: str = "nearest") -> DataFrame:
    """Another layer or label map on a patch's grid, by the stored map."""
    return warp_join(map_pixels(patches, size), layer, keys, width, height, method)


def validity(df: DataFrame, keys: list[str], max_rms: float, min_inside: float) -> DataFrame:
    """Patches whose corners fit and whose pixels lie inside the tile: (rms, inside share, valid)."""
    a = df.groupBy(*keys).agg(F.max("rms").alias("rms"), F.avg(F.col("inside").cast("int")).alias("inside"))
    return a.withColumn("valid", (F.col("rms") <= max_rms) & (F.col("inside") >= min_inside))


def inside_share(mapped: DataFrame, keys: list[str], width: int, height: int) -> DataFrame:
    """Share of a patch's pixels that lie inside the tile."""
    return mapped.groupBy(*keys).agg(F.avg(_inside(width, height).cast("int")).alias("inside"))


def three_four(points: list[Point]) -> Column:
    """Distance at the fourth corner between the map of three corners and that of all four."""
    x, y = points[3][0], points[3][1]
    return bound({"t": fit(points[:3]), "f": fit(points)}, lambda m: F.sqrt(_squared(apply(m["t"], x, y), apply(m["f"], x, y))))


def _squared(a: tuple[Column, Column], b: tuple[Column, Column]) -> Column:
    return (a[0] - b[0]) * (a[0] - b[0]) + (a[1] - b[1]) * (a[1] - b[1])


def warp_reverse(patches: DataFrame, cells: DataFrame, keys: list[str], size: int, width: int, height: int) -> DataFrame:
    """Baseline: the radar image on the optical grid, by the inverse map; what this does to its statistics is the reason against it."""
    back = patches.withColumn("map", invert(F.col("map"))).filter("map is not null")
    return warp_join(map_pixels(back, size), cells, keys, width, height)


def stretch_offset(mapped: DataFrame, keys: list[str], size: int, width: int, height: int) -> DataFrame:
    """Baseline without alignment, the tile stretched over the patch: mean distance in tile pixels from where the map puts a pixel."""
    u, v = F.col("x") * ((width - 1) / (size - 1)), F.col("y") * ((height - 1) / (size - 1))
    return mapped.groupBy(*keys).agg(F.avg(F.sqrt(_squared((F.col("pu"), F.col("pv")), (u, v)))).alias("offset"))
