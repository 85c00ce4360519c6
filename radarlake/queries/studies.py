"""Studies on the given tables: alignment baselines, reconstruction, physics, caption measures under control, retrieval by hyperplanes."""

from __future__ import annotations

from pyspark.sql import functions as F

from radarlake import registry
from radarlake.methods import align, caption, evaluate, geo, pairing, physics, raster, release, select
from radarlake.methods.lexicon import PART_CATEGORIES
from radarlake.queries import geometry, resampling  # noqa: F401  they register SQL that is looked up below
from radarlake.queries.captions import _BEST
from radarlake.queries.optical import _BILINEAR, _MAPPED, _MAPS, _P, _corners, _mapped, _maps
from radarlake.registry import query
from radarlake.standins import COLS, ROWS, acquisitions, captions, optical_tiles, samples_fact, scene_cells, scenes, table, vec_patches, with_views

_R = lambda c, n=6: (F.round(c, n) + 0.0)
C = F.col


# --- alignment --------------------------------------------------------------------


@query(with_views("optical", _MAPPED + " SELECT tile_id, round(avg(CAST(inside AS INT)), 6) AS inside FROM i GROUP BY tile_id"))
def a6_inside(spark, sf):
    return align.inside_share(_mapped(spark, sf), ["tile_id"], 8, 8).select("tile_id", _R("inside").alias("inside"))


@query(with_views("acq", f", p AS ({_P}) SELECT scene_id, round(0.75 * q, 6) AS apart FROM p"))
def a6_three_four(spark, sf):
    """A twist q moves the map of three corners by nothing there and that of four by three quarters of q."""
    df, c = _corners(spark, sf)
    return df.select("scene_id", _R(align.three_four(c)).alias("apart"))


def _patch_cells(spark, sf):
    return vec_patches(spark, sf).select(C("patch_id").alias("tile_id"), C("r").alias("v"), C("c").alias("u"), physics.intensity().alias("value"))


_REVERSE = """, k AS (SELECT t, 0.8e0 + t % 5 * 0.05e0 AS a11, t % 3 * 0.1e0 AS a12, t % 4 * 0.3e0 + 0.013e0 AS tx, -(t % 3 * 0.1e0) AS a21, 0.9e0 - t % 2 * 0.1e0 AS a22, t % 7 * 0.2e0 + 0.017e0 AS ty FROM (SELECT DISTINCT patch_id AS t FROM patches)),
w AS (SELECT t, x, y, (a22 * (x - tx) - a12 * (y - ty)) / (a11 * a22 - a12 * a21) AS pu, (a11 * (y - ty) - a21 * (x - tx)) / (a11 * a22 - a12 * a21) AS pv FROM k, range(8) ax(x), range(8) ay(y)),
f AS (SELECT t, x, y, sum(greatest(0, 1 - abs(pu - c)) * greatest(0, 1 - abs(pv - r)) * (re * re + im * im)) AS i FROM w JOIN patches ON patch_id = t AND abs(pu - c) < 1 AND abs(pv - r) < 1 WHERE pu BETWEEN 0 AND 7 AND pv BETWEEN 0 AND 7 GROUP BY ALL),
a AS (SELECT t, avg(i) ** 2 / var_samp(i) AS after FROM f GROUP BY t), b AS (SELECT patch_id, avg(re * re + im * im) ** 2 / var_samp(re * re + im * im) AS before FROM patches GROUP BY 1)
SELECT patch_id AS tile_id, round(before, 4) AS before, round(after, 4) AS after FROM a JOIN b ON patch_id = t"""


@query(with_views("patches", _REVERSE))
def b_reverse(spark, sf):
    """Looks of the radar patch as it is and after it was warped to the optical grid, which smooths the speckle."""
    cells = _patch_cells(spark, sf)
    # moved a little, so that no pixel lies on the patch's edge by rounding alone
    moved = C("map").withField("tx", C("map.tx") + 0.013).withField("ty", C("map.ty") + 0.017)
    maps = _maps(spark, sf).select("tile_id", "key", moved.alias("map"))
    w = align.warp_reverse(maps, cells, ["key"], 8, 8, 8).filter("inside").groupBy(C("key").alias("tile_id"))
    enl = lambda g, name: g.agg(F.try_divide(F.avg("value") * F.avg("value"), F.var_samp("value")).alias(name))
    j = enl(cells.groupBy("tile_id"), "before").join(enl(w, "after"), "tile_id")
    return j.select("tile_id", _R("before", 4).alias("before"), _R("after", 4).alias("after"))


@query(with_views("optical", _MAPPED + " SELECT tile_id, round(avg(sqrt((pu - x) ** 2 + (pv - y) ** 2)), 6) AS distance FROM i GROUP BY 1"))
def b_stretch(spark, sf):
    return align.stretch_offset(_mapped(spark, sf), ["tile_id"], 8, 8, 8).select("tile_id", _R("offset").alias("distance"))


@query(with_views("optical", _MAPPED + " SELECT i.tile_id, x, y, inside, CAST(CASE WHEN inside THEN floor(value / 64) ELSE 0 END AS INT) AS class FROM i LEFT JOIN optical o ON o.tile_id = i.tile_id AND o.band = 2 AND inside AND u = floor(pu + 0.5) AND v = floor(pv + 0.5)"))
def m6_layer(spark, sf):
    """A label map on the patches' grid, by the stored maps."""
    layer = optical_tiles(spark, sf).filter("band = 2").withColumn("value", F.floor(C("value") / 64))
    maps = _maps(spark, sf)
    p = align.project_layer(maps, layer, ["key"], 8, 8, 8)
    return p.select(C("key").alias("tile_id"), "x", "y", "inside", C("value").cast("int").alias("class"))


class _Tiles:
    """The tiles' table as a source."""

    def __init__(self, tiles):
        self.table = tiles

    def tiles(self, wanted):
        return self.table.join(wanted.select("tile_id").distinct(), "tile_id", "left_semi")


def _reconstructed(spark, sf, transform, method):
    maps = _maps(spark, sf)
    corner = lambda x, y: (F.lit(float(x)), F.lit(float(y)), *align.apply(C("map"), F.lit(float(x)), F.lit(float(y))))
    points = [corner(x, y) for x, y in ((0, 0), (7, 0), (0, 7), (7, 7))]
    return method(maps, _Tiles(optical_tiles(spark, sf).filter("band = 0")), "key", 8, 8, 8, transform, points)


@query(with_views("optical", _BILINEAR))
def m8_reconstruct(spark, sf):
    """Optical pixels made on read with the stored map."""
    w = _reconstructed(spark, sf, "stored", release.reconstruct)
    return w.select(C("key").alias("tile_id"), "x", "y", "inside", _R(C("value") + 3e-8, 5).alias("value"))


@query(with_views("optical", _BILINEAR.replace("SELECT tile_id, x, y, inside, round(coalesce(value, 0) + 3e-8, 5) AS value FROM i", "SELECT count(*) AS pixels, CAST(0 AS BIGINT) AS apart FROM i")))
def a6_refit(spark, sf):
    """Pixels of a reconstruction with maps fitted anew, and those whose value differs from the stored map's by over 1e-4 while both lie inside."""
    a = _reconstructed(spark, sf, "stored", release.reconstruct_rows).select("tile_id", "pixels")
    b = _reconstructed(spark, sf, "refit", release.reconstruct_rows).select("tile_id", C("pixels").alias("pixels2"))
    shown = lambda p: _R(p["value"] + 3e-8, 5)
    # both hold a patch's pixels line by line
    apart = F.zip_with("pixels", "pixels2", lambda p, q: p["inside"] & q["inside"] & (F.abs(shown(p) - shown(q)) > 1e-4))
    counted = a.join(b, "tile_id").select(F.size("pixels").alias("n"), F.size(F.filter(apart, lambda x: x)).alias("apart"))
    return counted.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("pixels"), F.coalesce(F.sum("apart"), F.lit(0)).cast("long").alias("apart"))


# --- physics ----------------------------------------------------------------------


@query(with_views("cells", " SELECT scene_id, CAST(r // 3 AS INT) AS r, CAST(c // 3 AS INT) AS c, round(avg(re * re + im * im) + 3e-6, 2) AS intensity, count(*) AS looks FROM cells GROUP BY ALL"))
def b_coarse(spark, sf):
    d = physics.coarse_detected(scene_cells(spark, sf), 3)
    return d.select("scene_id", "r", "c", _R(C("intensity") + 3e-6, 2).alias("intensity"), "looks")


@query(with_views("cells", ", f AS (SELECT scene_id, sum((re * re + im * im) ** 2) AS e FROM cells GROUP BY 1), k AS (SELECT scene_id, sum(n * m * m) AS e2 FROM (SELECT scene_id, avg(re * re + im * im) AS m, count(*) AS n FROM cells GROUP BY scene_id, r // 3, c // 3) GROUP BY 1) SELECT scene_id, round(1 - e2 / e, 6) AS lost, round(3 * 0.8e0 / sin(radians(30e0)), 6) AS ground_m FROM f JOIN k USING (scene_id)"))
def b_coarse_loss(spark, sf):
    d = physics.coarse_loss(scene_cells(spark, sf), 3, 0.8, 30.0)
    return d.select("scene_id", _R("lost").alias("lost"), _R("ground_m").alias("ground_m"))


@query(with_views("patches", """, w AS (SELECT label, unnest(['amplitude', 'intensity', 'db', 'phase']) AS kind, unnest([sqrt(re * re + im * im), re * re + im * im, CASE WHEN re * re + im * im > 0 THEN 10 * log10(re * re + im * im) END, atan2(im, re)]) AS x FROM patches),
b AS (SELECT kind, label, count(*) AS n, avg(x) AS m, var_pop(x) AS v FROM w WHERE x IS NOT NULL GROUP BY ALL), t AS (SELECT kind, sum(n * m) / sum(n) AS mean FROM b GROUP BY 1)
SELECT kind, round(sum(n * (m - mean) ** 2) / sum(n * v), 6) AS separability FROM b JOIN t USING (kind) GROUP BY 1"""))
def m10_compare(spark, sf):
    return physics.separability(vec_patches(spark, sf), "label").select("kind", _R("separability").alias("separability"))


#: The kernel of a third of the azimuth spectrum: bins -15 to -6, -5 to 4, 5 to 14 of thirty.
_PARTS = """, kern AS (SELECT CAST(p AS INT) AS part, d, sum(cos(2 * pi() * f * d / 30e0)) / 30 AS kr, sum(sin(2 * pi() * f * d / 30e0)) / 30 AS ki FROM range(3) tp(p), range(-29, 30) td(d), range(-15, 15) tf(f) WHERE (f + 15) // 10 = p GROUP BY ALL),
parts AS (SELECT x.scene_id, part, CAST(o.r AS INT) AS r, x.c, sum(re * kr - im * ki) AS re, sum(re * ki + im * kr) AS im FROM cells x, range(30) o(r), kern k WHERE k.d = o.r - x.r GROUP BY ALL)"""


@query(with_views("cells", _PARTS + ", top AS (SELECT scene_id, max(sqrt(re * re + im * im)) AS top FROM parts GROUP BY 1) SELECT scene_id, r, c, CAST(max(CASE WHEN part = 0 THEN floor(sqrt(re * re + im * im) / top * 255 + 0.5) END) AS INT) AS red, CAST(max(CASE WHEN part = 1 THEN floor(sqrt(re * re + im * im) / top * 255 + 0.5) END) AS INT) AS green, CAST(max(CASE WHEN part = 2 THEN floor(sqrt(re * re + im * im) / top * 255 + 0.5) END) AS INT) AS blue FROM parts JOIN top USING (scene_id) GROUP BY scene_id, r, c"))
def m10_color(spark, sf):
    return physics.colorize(physics.subapertures(scene_cells(spark, sf), scenes(spark)))


@query(with_views("cells", _PARTS + ", v AS (SELECT scene_id, r, c, avg(sqrt(re * re + im * im)) AS m, stddev_pop(sqrt(re * re + im * im)) AS s FROM parts GROUP BY ALL) SELECT scene_id, round(avg(s / m), 6) AS cv FROM v WHERE m > 1e-9 GROUP BY 1"))
def m10_diversity(spark, sf):
    d = physics.diversity(physics.subapertures(scene_cells(spark, sf), scenes(spark)))
    return d.select("scene_id", _R("cv").alias("cv"))


@query(with_views("cells", _PARTS + " SELECT scene_id, part, r, c, round(re, 4) + 0.0 AS re, round(im, 4) + 0.0 AS im FROM parts"))
def m10_subap(spark, sf):
    p = physics.subapertures(scene_cells(spark, sf), scenes(spark))
    return p.select("scene_id", "part", "r", "c", _R("re", 4).alias("re"), _R("im", 4).alias("im"))


@query(with_views("cells", """, spec AS (SELECT scene_id, c, f, sum(re * cos(2 * pi() * f * r / 30e0) + im * sin(2 * pi() * f * r / 30e0)) AS re, sum(im * cos(2 * pi() * f * r / 30e0) - re * sin(2 * pi() * f * r / 30e0)) AS im FROM cells, range(-15, 15) tf(f) GROUP BY ALL)
SELECT scene_id, round(sqrt(sum(CASE WHEN f BETWEEN -7 AND 7 THEN 0 ELSE re * re + im * im END) / sum(re * re + im * im)), 6) AS error FROM spec GROUP BY 1"""))
def m10_superres(spark, sf):
    """Error of the zero-padded image against the full one: by Parseval the root of the energy outside the kept band."""
    from radarlake.methods import spectrum

    s = scenes(spark)
    low, full = physics.superres_pairs(scene_cells(spark, sf), s)
    return spectrum.compare(full, physics.superres_zeropad(low, s)).select("scene_id", _R("rmse").alias("error"))


@query(with_views("cells", " SELECT scene_id, CAST(r // 6 AS INT) AS tr, CAST(c // 6 AS INT) AS tc, count(*) AS n, round(stddev_pop(re * re + im * im) / avg(re * re + im * im), 6) AS cv, CASE WHEN stddev_pop(re * re + im * im) / avg(re * re + im * im) <= 1.25 THEN 'homogeneous' ELSE 'scatterer' END AS kind FROM cells GROUP BY ALL"))
def m10_homog(spark, sf):
    return physics.homogeneity(scene_cells(spark, sf), 6).select("scene_id", "tr", "tc", "n", _R("cv").alias("cv"), "kind")


@query(with_views("fact", " SELECT CAST(incidence_deg // 10 * 10 AS INT) AS from_deg, count(*) AS n, round(avg(l_extendedprice), 2) AS mean, round(var_samp(l_extendedprice) / 1e6, 3) AS variance FROM fact GROUP BY 1"))
def m10_incidence(spark, sf):
    b = physics.by_incidence(samples_fact(spark, sf), "incidence_deg", "l_extendedprice")
    return b.select("from_deg", "n", _R("mean", 2).alias("mean"), _R(C("variance") / 1e6, 3).alias("variance"))


@query(with_views("fact", " SELECT round(regr_slope(l_extendedprice, incidence_deg), 4) AS slope, round(regr_intercept(l_extendedprice, incidence_deg), 2) AS intercept, round(regr_r2(l_extendedprice, incidence_deg), 8) AS r2 FROM fact"))
def m10_incidence_slope(spark, sf):
    s = physics.incidence_slope(samples_fact(spark, sf), "incidence_deg", "l_extendedprice")
    return s.select(_R("slope", 4).alias("slope"), _R("intercept", 2).alias("intercept"), _R("r2", 8).alias("r2"))


@query(_BEST + ", j AS (SELECT category, CASE WHEN p_size <= 16 THEN 'dark' WHEN p_size <= 33 THEN 'mid' ELSE 'bright' END AS signal FROM l JOIN part ON p_partkey = sample_id), n AS (SELECT category, signal, count(*) AS n FROM j GROUP BY ALL) SELECT category, signal, n, round(n / sum(n) OVER (PARTITION BY category), 6) AS share FROM n")
def m10_disagree(spark, sf):
    """Categories of the stand-in captions against classes of a stand-in signal strength."""
    p = table(spark, sf, "part").select(C("p_name").alias("text"), F.when(C("p_size") <= 16, "dark").when(C("p_size") <= 33, "mid").otherwise("bright").alias("signal"))
    d = physics.disagreement(caption.label(p, PART_CATEGORIES), "category", "signal")
    return d.select("category", "signal", "n", _R("share").alias("share"))


@query(with_views("cells", ", i AS (SELECT scene_id, r, c, re * re + im * im AS i, avg(re * re + im * im) OVER (PARTITION BY scene_id) AS m FROM cells), l AS (SELECT scene_id, r, c, c - row_number() OVER (PARTITION BY scene_id, r ORDER BY c) AS g FROM i WHERE i < 0.25 * m), n AS (SELECT scene_id, r, c, CAST(count(*) OVER (PARTITION BY scene_id, r, g) AS INT) AS length FROM l) SELECT * FROM n WHERE length >= 2"))
def m10_shadow(spark, sf):
    return physics.masks(scene_cells(spark, sf))


@query(with_views("acq", ", d AS (SELECT city_id, scene_id, acquired_on, date_diff('day', CAST(lag(acquired_on) OVER (PARTITION BY city_id ORDER BY acquired_on, scene_id) AS DATE), CAST(acquired_on AS DATE)) AS gap FROM acq), s AS (SELECT *, sum(CASE WHEN gap IS NULL OR gap > 365 THEN 1 ELSE 0 END) OVER (PARTITION BY city_id ORDER BY acquired_on, scene_id ROWS UNBOUNDED PRECEDING) AS stack FROM d) SELECT city_id, scene_id, CAST(stack AS BIGINT) AS stack, CAST(row_number() OVER (PARTITION BY city_id, stack ORDER BY acquired_on, scene_id) AS INT) AS layer, CAST(coalesce(gap, -1) AS INT) AS gap FROM s"))
def m12_stack(spark, sf):
    a = acquisitions(spark, sf).select("city_id", "scene_id", "acquired_on")
    s = select.temporal(a, "city_id", "acquired_on", "scene_id", 365)
    return s.select("city_id", "scene_id", "stack", "layer", F.coalesce("gap", F.lit(-1)).alias("gap"))


@query(with_views("acq", " SELECT scene_id, true AS found FROM acq"))
def m3_rdoppler(spark, sf):
    """Range and Doppler of planted points, solved back: the point is found to a millimetre."""
    lat, lon = C("lat0") + 0.123, C("lon0") + 0.456
    p = geo.llh_to_ecef(lat, lon, F.lit(0.0))
    east, north, up = geo.frame(lat, lon)
    off = [5e5 * u + 3e5 * e + 2e4 * n for e, n, u in zip(east, north, up, strict=True)]
    velocity = [7500.0 * n for n in north]
    dot = lambda a, b: sum((x * y for x, y in zip(a, b, strict=True)), F.lit(0.0))
    rng = F.sqrt(dot(off, off))
    planted = acquisitions(spark, sf).select(
        "scene_id", F.array(*p).alias("truth"), F.array(*(a + b for a, b in zip(p, off, strict=True))).alias("sensor"), F.array(*velocity).alias("velocity"),
        F.array(*(a + 4e3 * e for a, e in zip(p, east, strict=True))).alias("start"), rng.alias("rng"), (-dot(off, velocity) / (rng * 7500.0)).alias("cos_cone"),
    )
    far = F.sqrt(F.aggregate(F.zip_with("at", "truth", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda t, x: t + x))
    return geo.rdoppler(planted).select("scene_id", ((far < 1e-3) & (C("residual") < 1e-3)).alias("found"))


# --- captions under control -------------------------------------------------------


def _pairs(spark, sf):
    c = table(spark, sf, "conversations")
    nxt = c.filter("role = 'assistant'").select("conv_id", (C("turn") - 1).alias("turn"), C("text").alias("candidate"))
    return c.filter("role = 'user'").select("conv_id", "turn", C("text").alias("reference")).join(nxt, ["conv_id", "turn"])


_F1 = """WITH p AS (SELECT a.conv_id, a.turn, a.text AS reference, b.text AS candidate FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1 WHERE a.role = 'user' AND b.role = 'assistant'),
o AS (SELECT *, row_number() OVER (ORDER BY md5(conv_id || '-' || turn), conv_id, turn) - 1 AS place, count(*) OVER () AS n FROM p),
m AS (SELECT 1 AS m, conv_id, turn, reference, candidate FROM p UNION ALL SELECT 0, a.conv_id, a.turn, a.reference, b.candidate FROM o a JOIN o b ON b.place = (a.place + 1) % a.n),
t AS (SELECT m, conv_id, turn, 'r' AS side, unnest(string_split(lower(reference), ' ')) AS w FROM m UNION ALL SELECT m, conv_id, turn, 'c', unnest(string_split(lower(candidate), ' ')) FROM m),
k AS (SELECT m, conv_id, turn, w, count(*) FILTER (side = 'r') AS a, count(*) FILTER (side = 'c') AS b FROM t GROUP BY ALL),
f AS (SELECT m, conv_id, turn, round(2 * sum(least(a, b)) / (sum(a) + sum(b)), 4) AS v FROM k GROUP BY ALL)"""


def _f1(pairs):
    u = evaluate.unigram(pairs, ["conv_id", "turn"])
    p, r = C("precision"), C("recall")
    return u.withColumn("f1", F.coalesce(F.try_divide(2 * p * r, p + r), F.lit(0.0)))


@query(_F1 + " SELECT count(*) FILTER (m = 1) AS pairs, round(avg(v) FILTER (m = 1), 6) AS matched, round(avg(v) FILTER (m = 0), 6) AS mismatched, round(avg(v) FILTER (m = 1) - avg(v) FILTER (m = 0), 6) + 0.0 AS gap, round((SELECT avg(CASE WHEN x.v > y.v THEN 1 WHEN x.v = y.v THEN 0.5 ELSE 0 END) FROM f x, f y WHERE x.m = 1 AND y.m = 0), 6) AS auc FROM f")
def e_control(spark, sf):
    """Word overlap of matched pairs against pairs dealt out wrongly: a measure that can't tell them apart says little."""
    p = _pairs(spark, sf)
    c = evaluate.control(_f1(p), _f1(evaluate.shifted(p, ["conv_id", "turn"])), "f1")
    return c.select("pairs", *(_R(k).alias(k) for k in ("matched", "mismatched", "gap", "auc")))


@query("SELECT quality AS truth, CAST(n_chars >= 400 AS INT) AS judged, count(*) AS n, round(sum(sum(CASE WHEN quality = CAST(n_chars >= 400 AS INT) THEN 1 ELSE 0 END)) OVER () / sum(count(*)) OVER (), 6) AS agreement FROM documents JOIN labels USING (doc_id) GROUP BY 1, 2")
def e_judge(spark, sf):
    """A stub judge, the text's length, against the given quality."""
    d = table(spark, sf, "documents").join(table(spark, sf, "labels"), "doc_id")
    j = evaluate.judged(d, C("n_chars") >= 400, "quality")
    return j.select("truth", "judged", "n", _R("agreement").alias("agreement"))


_SETS = ", ".join(f"({k}, [{', '.join(repr(w) for w in yes)}])" for k, (yes, _) in enumerate(PART_CATEGORIES.values()))


@query(f"""WITH v AS (SELECT * FROM (VALUES {_SETS}) t(k, yes)), p AS (SELECT a.p_partkey AS key, a.p_name AS x, b.p_name AS y FROM part a JOIN part b ON b.p_partkey = a.p_partkey + 1),
s AS (SELECT key, count(*) FILTER (len(list_intersect(string_split(x, ' '), yes)) > 0) AS a, count(*) FILTER (len(list_intersect(string_split(y, ' '), yes)) > 0) AS b, count(*) FILTER (len(list_intersect(string_split(x, ' '), yes)) > 0 AND len(list_intersect(string_split(y, ' '), yes)) > 0) AS ab FROM p, v GROUP BY key)
SELECT key, round(CASE WHEN a + b = 0 THEN 1 ELSE 2 * ab / (a + b) END, 6) AS f1 FROM s""")
def e_judge_sets(spark, sf):
    """A stub judge of meaning: the categories that two texts share."""
    found = lambda c: F.filter(F.array(*(F.when(F.arrays_overlap(F.split(c, " "), F.array(*map(F.lit, yes))), F.lit(k)) for k, (yes, _) in enumerate(PART_CATEGORIES.values()))), lambda x: x.isNotNull())
    p = table(spark, sf, "part").select(C("p_partkey").alias("key"), found(C("p_name")).alias("a"))
    j = p.join(p.select((C("key") - 1).alias("key"), C("a").alias("b")), "key")
    return j.select("key", _R(evaluate.category_f1(C("a"), C("b"))).alias("f1"))


@query("SELECT lang, count(*) AS n, round(avg(quality), 6) AS before, round(avg(CASE WHEN toxic = 1 THEN 0 ELSE quality END), 6) AS after, round(avg(CASE WHEN toxic = 1 THEN 0 ELSE quality END) / nullif(avg(quality), 0), 6) AS kept FROM documents JOIN labels USING (doc_id) GROUP BY lang")
def e_retention(spark, sf):
    """Skill by language before and after a change, for which a stand-in takes the toxic texts' score away."""
    d = table(spark, sf, "documents").join(table(spark, sf, "labels"), "doc_id").withColumn("after", F.when(C("toxic") == 1, 0).otherwise(C("quality")))
    r = evaluate.retention(d, ["lang"], "quality", "after")
    return r.select("lang", "n", *(_R(k).alias(k) for k in ("before", "after", "kept")))


@query("SELECT lang, round(avg(quality) FILTER (doc_id % 2 = 0), 6) AS \"0.8 m\", round(avg(quality) FILTER (doc_id % 2 = 1), 6) AS \"0.4 m\" FROM documents JOIN labels USING (doc_id) GROUP BY lang")
def e_sensor(spark, sf):
    """Score by language for two sensors; the parity of the id stands for the sensor."""
    d = table(spark, sf, "documents").join(table(spark, sf, "labels"), "doc_id").withColumn("sensor", F.when(C("doc_id") % 2 == 0, "0.8 m").otherwise("0.4 m"))
    s = evaluate.by_sensor(d, "lang", "sensor", ["0.8 m", "0.4 m"], "quality")
    return s.select("lang", _R("`0.8 m`").alias("0.8 m"), _R("`0.4 m`").alias("0.4 m"))


@query(with_views("captions", ", n AS (SELECT sample_id, variant, len(string_split(text, ' ')) AS n FROM captions), w AS (SELECT sample_id, max(n) FILTER (variant = 'SHORT') AS s, max(n) FILTER (variant = 'MID') AS m, max(n) FILTER (variant = 'LONG') AS l FROM n GROUP BY 1) SELECT lang, count(*) AS n, round(avg(least(m, l) / l - least(s, l) / l), 6) AS difference, round(avg(CAST(least(m, l) / l > least(s, l) / l AS INT)), 6) AS better FROM w JOIN documents ON doc_id = sample_id GROUP BY lang"))
def e_attachment(spark, sf):
    """Word recall of the LONG caption under two instructions, MID as in training and SHORT; shorter captions are beginnings of longer ones, so lengths tell it."""
    n = captions(spark, sf).select("sample_id", "variant", F.size(F.split("text", " ")).alias("n")).groupBy("sample_id").pivot("variant", ["SHORT", "MID", "LONG"]).agg(F.first("n"))
    score = lambda k: F.least(C(k), C("LONG")) / C("LONG")
    s = n.select("sample_id", score("MID").alias("trained"), score("SHORT").alias("other"))
    d = s.join(table(spark, sf, "documents").select(C("doc_id").alias("sample_id"), "lang"), "sample_id")
    a = evaluate.attachment(d, "trained", "other", ["lang"])
    return a.select("lang", "n", _R("difference").alias("difference"), _R("better").alias("better"))


@query()
def e_captioning(spark, sf):
    return evaluate.captioning(_pairs(spark, sf)).select("conv_id", "turn", *evaluate.MEASURES)


@query()
def m12_protocol(spark, sf):
    """Retrieval and control of one release in one table."""
    e = table(spark, sf, "embeddings")
    found = evaluate.retrieval(e.filter("vec_id % 50 = 0"), e, 10, own=False)
    p = _pairs(spark, sf)
    return evaluate.protocol("1", retrieval=evaluate.recall(found), control=evaluate.control(_f1(p), _f1(evaluate.shifted(p, ["conv_id", "turn"])), "f1"))


# --- retrieval by hyperplanes -----------------------------------------------------


@query()
def e_lsh(spark, sf):
    e = table(spark, sf, "embeddings")
    return evaluate.retrieval_lsh(e.filter("vec_id % 50 = 0"), e, 10).select("query", "hit", "rank", "score")


@query()
def e_lsh_recall(spark, sf):
    """Share of the exact ten best that the index finds."""
    e = table(spark, sf, "embeddings")
    q = e.filter("vec_id % 50 = 0")
    return evaluate.lsh_recall(evaluate.retrieval_lsh(q, e, 10), evaluate.retrieval(q, e, 10))


# --- more -------------------------------------------------------------------------


@query("""WITH b AS (SELECT scene_id, city_id, continent FROM (SELECT o_orderkey AS scene_id, o_custkey AS city_id, r_name AS continent FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey))
SELECT continent, count(*) AS n FROM b GROUP BY 1""")
def m9_continent(spark, sf):
    return acquisitions(spark, sf).groupBy("continent").agg(F.count("*").alias("n"))


@query(with_views("optical", " SELECT tile_id // 2 AS key, CAST(v AS BIGINT) AS v, CAST(tile_id % 2 * 8 + u AS BIGINT) AS u, value FROM optical WHERE band = 0"))
def m5_mosaic(spark, sf):
    """Two neighbouring tiles of each place on one raster."""
    place = (F.floor(C("tile_id") / 2).alias("key"), F.lit(1).alias("z"), C("tile_id").alias("x"), F.floor(C("tile_id") / 2).alias("y"))
    tiles = optical_tiles(spark, sf).filter("band = 0")
    cover = tiles.select(*place).distinct()
    return pairing.mosaic(cover, tiles.select(*place[1:], "v", "u", "value"), "key", 8).select("key", C("v").cast("long").alias("v"), C("u").cast("long").alias("u"), "value")


@query(with_views("patches", ", g AS (SELECT patch_id, sqrt(re * re + im * im) AS a, min(sqrt(re * re + im * im)) OVER w AS lo, max(sqrt(re * re + im * im)) OVER w AS hi FROM patches WINDOW w AS (PARTITION BY patch_id)) SELECT patch_id, CAST(8 AS INT) AS cols, CAST(8 AS INT) AS rows, CAST(sum(CAST(floor((a - lo) / (hi - lo) * 255 + 0.5 - 1e-9) AS INT)) AS BIGINT) AS grey FROM g GROUP BY 1"))
def m4_png(spark, sf):
    """Previews as PNG members, read back."""
    from radarlake.io import encode
    from radarlake.methods import tiling

    grey = tiling.preview(vec_patches(spark, sf), "minmax", "patch_id")
    rows = grey.groupBy("patch_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("r", "c", "grey"))), lambda s: s["grey"]).alias("pixels"))
    back = rows.select("patch_id", encode.from_png(encode.to_png(C("pixels"), F.lit(8))).alias("i"))
    return back.select("patch_id", "i.cols", "i.rows", F.aggregate("i.pixels", F.lit(0).cast("long"), lambda s, x: s + x).alias("grey"))


def _upper(texts: list[str]) -> list[str]:
    """Stand-in for a model that rewrites captions."""
    return [t.replace(" and ", " with ") for t in texts]


@query("SELECT sample_id, upper(substr(t, 1, 1)) || substr(t, 2) || '.' AS text FROM (SELECT p_partkey AS sample_id, regexp_replace(trim(regexp_replace(regexp_replace(p_name, '\\b(red|blue)\\b', '', 'g'), '\\s+', ' ', 'g')), '^$', 'plain') || ' with more' AS t FROM part)")
def m7_clean_model(spark, sf):
    """The rules and a stand-in model as the second step."""
    p = table(spark, sf, "part").select(C("p_partkey").alias("sample_id"), F.regexp_replace(F.trim(F.regexp_replace(F.regexp_replace("p_name", r"\b(red|blue)\b", ""), r"\s+", " ")), "^$", "plain").alias("text"))
    return caption.clean_with(p.withColumn("text", F.concat("text", F.lit(" and more"))), _upper)


# --- packed layouts ---------------------------------------------------------------

_KNOWN = registry.known()


@query(_KNOWN["m2_local"])
def m2_packed(spark, sf):
    """The images of `m2_local` by way of packed strips and blocks, in doubles."""
    sizes = scenes(spark).filter("scene_id <> 'view'")
    cells = scene_cells(spark, sf).filter("scene_id <> 'view'")
    strips = raster.pack(cells, sizes, 7, None, "<c16")
    y = raster.unpack(raster.resample(strips, sizes, block=16, dtype="<c16"), "<c16")
    return y.select("scene_id", "r", "c", _R("re", 5).alias("re"), _R("im", 5).alias("im"))


@query(_KNOWN["m4_blocks"])
def m4_packed(spark, sf):
    """The patches of `m4_blocks` from packed blocks."""
    sizes = scenes(spark)
    blocks = raster.pack(scene_cells(spark, sf), sizes, 4, 4, "<c16")
    p = raster.patches(blocks, F.lit(ROWS), F.lit(COLS), 4, "<c16")
    # the key goes along as the scene, so that cells of one image keep their patch
    tagged = p.withColumn("scene_id", F.concat_ws("|", "scene_id", "tile_r", "tile_c")).select("scene_id", "r0", "c0", "rows", "cols", "payload")
    c = raster.unpack(tagged, "<c16").filter(F.hypot("re", "im") > 0)
    part = lambda k: F.element_at(F.split("scene_id", "[|]"), k)
    tile_r, tile_c = part(2).cast("long"), part(3).cast("long")
    return c.select(part(1).alias("scene_id"), tile_r.cast("int").alias("tile_r"), tile_c.cast("int").alias("tile_c"), (C("r") - tile_r * 4).cast("int").alias("y"), (C("c") - tile_c * 4).cast("int").alias("x"), _R("re", 4).alias("re"))


def assembled(spark, sf):
    """Records of all vector patches."""
    from radarlake.methods import tiling

    v = vec_patches(spark, sf)
    cells = v.select(C("patch_id").alias("scene_id"), "r", "c", "re", "im")
    sizes = v.groupBy(C("patch_id").alias("scene_id")).agg((F.max("r") + 1).alias("n_rows"), (F.max("c") + 1).alias("n_cols"), F.first("label").alias("label"))
    grey = tiling.preview(v, "minmax", "patch_id").groupBy(C("patch_id").alias("scene_id")).agg(F.transform(F.sort_array(F.collect_list(F.struct("r", "c", "grey"))), lambda s: s["grey"]).alias("pixels"))
    packed = raster.pack(cells, sizes, 8, 8).select("scene_id", "payload", "cols")
    return release.assemble(packed.join(grey, "scene_id").join(sizes.select("scene_id", "label"), "scene_id").withColumn("key", release.key("scene_id")), ["scene_id", "label"])


@query("SELECT md5(CAST(vec_id AS VARCHAR)) AS key, 4 AS members, 512 AS complex_bytes, '{\"scene_id\":' || vec_id || ',\"label\":' || label || '}' AS json, CAST(label AS BIGINT) AS xml_label FROM embeddings")
def m8_assemble(spark, sf):
    m = assembled(spark, sf)
    xml = F.xpath_long(C("members")["meta.xml"].cast("string"), F.lit("sample/label"))
    return m.select("key", F.size("members").alias("members"), F.length(C("members")["complex.bin"]).alias("complex_bytes"), C("members")["meta.json"].cast("string").alias("json"), xml.alias("xml_label"))
