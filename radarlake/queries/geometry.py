"""Geolocation and tiling on the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from radarlake.methods import geo, spectrum, tiling
from radarlake.registry import query
from radarlake.standins import COLS, ROWS, acquisitions, event_scenes, scene_cells, scenes, table, with_views

_R = lambda c, n=6: (F.round(c, n) + 0.0)
_ECEF = f"(6378137.0::DOUBLE / sqrt(1 - {geo.E2!r}::DOUBLE * sin(radians({{lat}})) ** 2))"


def _ecef_sql(lat: str, lon: str, h: str) -> tuple[str, str, str]:
    n = _ECEF.format(lat=lat)
    return f"({n} + {h}) * cos(radians({lat})) * cos(radians({lon}))", f"({n} + {h}) * cos(radians({lat})) * sin(radians({lon}))", f"({n} * (1 - {geo.E2!r}::DOUBLE) + {h}) * sin(radians({lat}))"


#: Geodetic coordinates by repeated latitude updates, another way than the engine's.
def _llh_sql(source: str, rounds: int = 12) -> str:
    steps = [f"s0 AS (SELECT *, sqrt(x * x + y * y) AS p, atan2(z, sqrt(x * x + y * y) * (1 - {geo.E2!r}::DOUBLE)) AS f0 FROM {source})"]
    for k in range(1, rounds + 1):
        n = f"(6378137.0::DOUBLE / sqrt(1 - {geo.E2!r}::DOUBLE * sin(f{k - 1}) ** 2))"
        steps.append(f"s{k} AS (SELECT *, atan2(z + {geo.E2!r}::DOUBLE * {n} * sin(f{k - 1}), p) AS f{k} FROM s{k - 1})")
    return ", ".join(steps) + f", llh AS (SELECT *, degrees(f{rounds}) AS lat, degrees(atan2(y, x)) AS lon FROM s{rounds})"


_GRID = ", p AS (SELECT *, greatest(1, CAST(floor(n_rows * native_az_m / 0.8::DOUBLE + 0.5) AS INT)) AS m_rows, greatest(1, CAST(floor(n_cols * native_rg_m / 0.8::DOUBLE + 0.5) AS INT)) AS m_cols FROM event_scenes), grid AS (SELECT scene_id, CAST(r AS INT) AS r, CAST(c AS INT) AS c, (r - n_rows // 2 * m_rows / n_rows::DOUBLE) AS dr, (c - n_cols // 2 * m_cols / n_cols::DOUBLE) AS dc, n_rows, n_cols, m_rows, m_cols, n_rows * native_az_m / m_rows AS az, n_cols * native_rg_m / m_cols AS rg FROM p, range(100) tr(r), range(100) tc(c) WHERE r < m_rows AND c < m_cols)"


@query(with_views("event_scenes", _GRID + " SELECT scene_id, r, c, round(dr * n_rows / m_rows, 6) + 0.0 AS native_row, round(dc * n_cols / m_cols, 6) + 0.0 AS native_col, round(dr * az, 6) + 0.0 AS az_m, round(dc * rg, 6) + 0.0 AS rg_m FROM grid"))
def m3_grid(spark, sf):
    g = geo.image_grid(spectrum.plan(event_scenes(spark, sf)))
    return g.select("scene_id", "r", "c", *(_R(k).alias(k) for k in ("native_row", "native_col", "az_m", "rg_m")))


def _heights(spark, sf):
    h = (F.col("city_id") % 9000).cast("double") - 400
    return acquisitions(spark, sf).select("scene_id", (F.col("lat0") + 0.123).alias("lat"), (F.col("lon0") + 0.456).alias("lon"), h.alias("h"))


_HEIGHTS = ", g AS (SELECT scene_id, lat0 + 0.123::DOUBLE AS lat, lon0 + 0.456::DOUBLE AS lon, CAST(city_id % 9000 AS DOUBLE) - 400 AS h FROM acq)"
_X, _Y, _Z = _ecef_sql("lat", "lon", "h")


@query(with_views("acq", f"{_HEIGHTS} SELECT scene_id, round({_X}, 3) AS x, round({_Y}, 3) AS y, round({_Z}, 3) AS z FROM g"))
def m3_ecef(spark, sf):
    x = geo.llh_to_ecef(F.col("lat"), F.col("lon"), F.col("h"))
    return _heights(spark, sf).select("scene_id", *(_R(c, 3).alias(k) for c, k in zip(x, "xyz", strict=True)))


@query(with_views("acq", f"{_HEIGHTS} SELECT scene_id, round(lat, 7) AS lat, round(lon, 7) AS lon, round(h, 3) AS h FROM g"))
def m3_llh(spark, sf):
    x = geo.llh_to_ecef(F.col("lat"), F.col("lon"), F.col("h"))
    at = _heights(spark, sf).select("scene_id", *(c.alias(k) for c, k in zip(x, "xyz", strict=True)))
    back = geo.ecef_to_llh(F.col("x"), F.col("y"), F.col("z"))
    return at.select("scene_id", *(_R(c, n).alias(k) for c, k, n in zip(back, ("lat", "lon", "h"), (7, 7, 3), strict=True)))


@query(with_views("acq", "SELECT count(*) AS points, true AS below_tenth_mm FROM acq"))
def a3_roundtrip(spark, sf):
    x = geo.llh_to_ecef(F.col("lat"), F.col("lon"), F.col("h"))
    at = _heights(spark, sf).select(*(c.alias(k) for c, k in zip(x, "xyz", strict=True)))
    back = geo.llh_to_ecef(*geo.ecef_to_llh(F.col("x"), F.col("y"), F.col("z")))
    return at.agg(F.count("*").alias("points"), (F.max(geo.metres_apart(back, (F.col("x"), F.col("y"), F.col("z")))) < 1e-4).alias("below_tenth_mm"))


#: The point 512 samples on in both directions: offset along north, and along east on the ground (slant / sin).
_NORTH = "(-sin(radians(lat0)) * cos(radians(lon0)), -sin(radians(lat0)) * sin(radians(lon0)), cos(radians(lat0)))"
_S = [c for c in _ecef_sql("lat0", "lon0", "0")]
_POINT = f""", q AS (SELECT scene_id, lat0, lon0,
 {_S[0]} + a * (-sin(radians(lat0)) * cos(radians(lon0))) + g * (-sin(radians(lon0))) AS x,
 {_S[1]} + a * (-sin(radians(lat0)) * sin(radians(lon0))) + g * cos(radians(lon0)) AS y,
 {_S[2]} + a * cos(radians(lat0)) AS z, a, g FROM (SELECT *, 512 * 0.8::DOUBLE * sa AS a, 512 * 0.8::DOUBLE * sg / sin(radians(incidence_deg)) AS g FROM acq, (VALUES (-1), (1)) ta(sa), (VALUES (-1), (1)) tg(sg)))"""


@query(with_views("acq", f"{_POINT} SELECT scene_id, round(x, 3) AS x, round(y, 3) AS y, round(z, 3) AS z FROM q WHERE a > 0 AND g > 0"))
def m3_plane(spark, sf):
    lat, lon = F.col("lat0"), F.col("lon0")
    u_az, u_rg = geo.slant_axes(lat, lon, F.col("incidence_deg"))
    d = F.lit(512 * 0.8)
    at = geo.plane_to_ecef(geo.llh_to_ecef(lat, lon, F.lit(0.0)), u_az, u_rg, d, d, geo.frame(lat, lon)[2])
    return acquisitions(spark, sf).select("scene_id", *(_R(c, 3).alias(k) for c, k in zip(at, "xyz", strict=True)))


_BOX = f"{_POINT}, {_llh_sql('q')}, box AS (SELECT scene_id, min(lat) AS south, max(lat) AS north, min(lon) AS lo, max(lon) AS hi, min(CASE WHEN lon < 0 THEN lon + 360 ELSE lon END) AS lo2, max(CASE WHEN lon < 0 THEN lon + 360 ELSE lon END) AS hi2 FROM llh GROUP BY scene_id)"


def boxes(spark, sf):
    d = F.lit(512 * 0.8)
    return geo.patch_bbox(acquisitions(spark, sf), -d, d, -d, d)


@query(with_views("acq", f"{_BOX} SELECT scene_id, round(south, 6) AS south, round(north, 6) AS north, round(CASE WHEN hi - lo > 180 THEN CASE WHEN lo2 > 180 THEN lo2 - 360 ELSE lo2 END ELSE lo END, 6) AS west, round(CASE WHEN hi - lo > 180 THEN CASE WHEN hi2 > 180 THEN hi2 - 360 ELSE hi2 END ELSE hi END, 6) AS east, hi - lo > 180 AS wraps FROM box"))
def m3_bbox(spark, sf):
    return boxes(spark, sf).select("scene_id", *(_R(k).alias(k) for k in ("south", "north", "west", "east")), "wraps")


@query(with_views("acq", f"{_BOX} SELECT wraps, count(*) AS boxes, CAST(sum(CASE WHEN wraps THEN 2 ELSE 1 END) AS BIGINT) AS ranges FROM (SELECT hi - lo > 180 AS wraps FROM box) GROUP BY 1"))
def m3_wrap(spark, sf):
    b = boxes(spark, sf).withColumn("parts", F.size(geo.wrap_bbox(F.col("west"), F.col("east"))))
    return b.groupBy("wraps").agg(F.count("*").alias("boxes"), F.sum("parts").alias("ranges"))


@query(with_views("acq", "SELECT scene_id, CAST(incidence_deg AS DOUBLE) AS ellipsoid, CAST(incidence_deg - city_id % 5 AS DOUBLE) AS terrain, round(CASE WHEN scene_id % 2 = 0 THEN incidence_deg + 0.25 ELSE incidence_deg - city_id % 5 END, 6)::DOUBLE AS best FROM acq"))
def m3_incidence(spark, sf):
    slope = (F.col("city_id") % 5).cast("double")
    product = F.when(F.col("scene_id") % 2 == 0, F.col("incidence_deg") + 0.25)
    return acquisitions(spark, sf).select("scene_id", _R(geo.incidence("ellipsoid")).alias("ellipsoid"), _R(geo.incidence("terrain", slope)).alias("terrain"), _R(geo.incidence("any", slope, product)).alias("best"))


@query(with_views("acq", "SELECT incidence_deg, count(*) AS scenes, round(1024 * 0.8::DOUBLE / sin(radians(incidence_deg)), 6) AS ground_m FROM acq GROUP BY incidence_deg"))
def m3_ground(spark, sf):
    return acquisitions(spark, sf).groupBy("incidence_deg").agg(F.count("*").alias("scenes")).withColumn("ground_m", _R(geo.ground_extent(F.lit(1024 * 0.8), F.col("incidence_deg"))))


_SIZES = ", s AS (SELECT scene_id, CAST(1000 + scene_id % 3000 AS INT) AS rows, CAST(1000 + scene_id * 7 % 2500 AS INT) AS cols FROM acq)"


def _sized(spark, sf):
    return acquisitions(spark, sf).select("scene_id", (F.lit(1000) + F.col("scene_id") % 3000).cast("int").alias("m_rows"), (F.lit(1000) + F.col("scene_id") * 7 % 2500).cast("int").alias("m_cols"))


def _index(name: str, edge: str, axis: str):
    def run(spark, sf):
        return tiling.index(_sized(spark, sf), edge=edge).select("scene_id", "row0", "col0")

    sql = f"{_SIZES}, r AS (SELECT scene_id, CAST(o AS INT) AS row0 FROM s, {axis.format(n='rows')}), c AS (SELECT scene_id, CAST(o AS INT) AS col0 FROM s, {axis.format(n='cols')}) SELECT scene_id, row0, col0 FROM r JOIN c USING (scene_id)"
    query(with_views("acq", sql), name)(run)


_index("m4_index", "drop", "(SELECT unnest(range(0, 10)) * 512 AS o) WHERE o + 1024 <= {n}")
_index("m4_index_shift", "shift", "LATERAL (SELECT o FROM (SELECT unnest(range(0, 10)) * 512 AS o) WHERE o + 1024 <= {n} UNION SELECT {n} - 1024 WHERE {n} > 1024)")
_index("m4_index_pad", "pad", "(SELECT unnest(range(0, 10)) * 512 AS o) WHERE o = 0 OR o - 512 + 1024 < {n}")
_TILES = ", t AS (SELECT scene_id, CAST(a AS INT) AS tile_r, CAST(b AS INT) AS tile_c, r, c, re, im, CAST(r - a * 4 AS INT) AS y, CAST(c - b * 4 AS INT) AS x FROM cells, range(0, 6) ta(a), range(0, 5) tb(b) WHERE r BETWEEN a * 4 AND a * 4 + 7 AND c BETWEEN b * 4 AND b * 4 + 7)"


def tiles(spark, sf):
    return tiling.explode_cells(scene_cells(spark, sf), 8, 4, F.lit(ROWS), F.lit(COLS))


@query(with_views("cells", f"{_TILES} SELECT scene_id, tile_r, tile_c, y, x, round(re, 4) AS re FROM t"))
def m4_cells(spark, sf):
    return tiles(spark, sf).select("scene_id", "tile_r", "tile_c", "y", "x", _R("re", 4).alias("re"))


@query(with_views("cells", f"{_TILES} SELECT scene_id, tile_r, tile_c, y, x, round(re, 4) AS re FROM t"))
def m4_blocks(spark, sf):
    return tiling.from_blocks(scene_cells(spark, sf), 4, F.lit(ROWS), F.lit(COLS)).select("scene_id", "tile_r", "tile_c", "y", "x", _R("re", 4).alias("re"))


@query(with_views("cells", f"{_TILES} SELECT scene_id, tile_r, tile_c, count(*) / 64 AS valid, round(avg(sqrt(re * re + im * im)), 4) AS amplitude FROM t GROUP BY ALL HAVING count(*) / 64 >= 0.9"))
def m4_select(spark, sf):
    return tiling.select(tiles(spark, sf), 8, min_valid=0.9).withColumn("amplitude", _R("amplitude", 4))


@query(with_views("cells", "SELECT scene_id, r, c, round(sqrt(re * re + im * im), 5) AS amplitude FROM cells"))
def m4_amp(spark, sf):
    return scene_cells(spark, sf).select("scene_id", "r", "c", _R(tiling.amplitude(), 5).alias("amplitude"))


def _preview(how: str, ends: str, x: str):
    sql = f", a AS (SELECT *, sqrt(re * re + im * im) AS a FROM cells), e AS (SELECT scene_id, {ends} FROM a GROUP BY scene_id) SELECT scene_id, r, c, CAST(floor(greatest(0.0, least(1.0, {x})) * 255 + 0.5 - 1e-9) AS INT) AS grey FROM a JOIN e USING (scene_id)"
    query(with_views("cells", sql), f"m4_prev_{how}")(lambda spark, sf: tiling.preview(scene_cells(spark, sf), {"pct": "percentile"}.get(how, how)).select("scene_id", "r", "c", "grey"))


_preview("minmax", "min(a) AS lo, max(a) AS hi", "(a - lo) / (hi - lo)")
_preview("pct", "quantile_cont(a, 0.01) AS lo, quantile_cont(a, 0.99) AS hi", "(a - lo) / (hi - lo)")
_preview("db", "0 AS lo, max(a) AS hi", "(20 * log10(greatest(a / hi, 1e-12)) + 40) / 40")


@query("SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(sum(value), 2) AS total FROM (SELECT value, date_trunc('hour', ts) - INTERVAL (k) HOUR AS s FROM events, range(2) t(k)) GROUP BY 1")
def m4_series(spark, sf):
    w = tiling.series(table(spark, sf, "events"), "ts", "2 hours", "1 hour")
    return w.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n", _R("total", 2).alias("total"))


@query(with_views("cells", f"{_TILES} SELECT scene_id, count(DISTINCT tile_r * 100 + tile_c) AS patches, round(count(*) / (SELECT count(*) FROM cells c WHERE c.scene_id = t.scene_id), 6) AS duplication, round(count(DISTINCT r * 100 + c) / (SELECT count(*) FROM cells c WHERE c.scene_id = t.scene_id), 6) AS coverage FROM t GROUP BY scene_id"))
def a4_overlap(spark, sf):
    t = tiles(spark, sf).groupBy("scene_id").agg(F.count_distinct("tile_r", "tile_c").alias("patches"), F.count("*").alias("rows"), F.count_distinct("r", "c").alias("seen"))
    n = scene_cells(spark, sf).groupBy("scene_id").agg(F.count("*").alias("n"))
    return t.join(n, "scene_id").select("scene_id", "patches", _R(F.col("rows") / F.col("n")).alias("duplication"), _R(F.col("seen") / F.col("n")).alias("coverage"))
