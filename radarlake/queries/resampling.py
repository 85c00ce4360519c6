"""Resampling by spectrum, its baselines and its measures, on the event scenes."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F

from radarlake.methods import spectrum
from radarlake.registry import query
from radarlake.standins import acquisitions, event_scenes, scene_cells, scenes, table, with_views

_R = lambda c, n=6: (F.round(c, n) + 0.0)
#: Sizes in SQL, and images by the sum over all kept frequencies.
_PLAN = """SELECT *, greatest(1, CAST(floor(n_rows * native_az_m / 0.8::DOUBLE + 0.5) AS INT)) AS m_rows, greatest(1, CAST(floor(n_cols * native_rg_m / 0.8::DOUBLE + 0.5) AS INT)) AS m_cols FROM {src}"""
_DIR = "CASE WHEN m_rows < n_rows THEN 'down' WHEN m_rows > n_rows THEN 'up' ELSE 'identity' END"
_DIR2 = "CASE WHEN m_cols < n_cols THEN 'down' WHEN m_cols > n_cols THEN 'up' ELSE 'identity' END"


def _axis(n: str, m: str) -> str:
    angle = f"2 * pi() * f * (i / {m}::DOUBLE - j / {n}::DOUBLE)"
    return f"SELECT scene_id, i, j, sum(cos({angle})) / {n} AS kr, sum(sin({angle})) / {n} AS ki FROM p, range(200) ti(i), range(200) tj(j), range(-100, 100) tf(f) WHERE i < {m} AND j < {n} AND f >= -(least({n}, {m}) // 2) AND f < least({n}, {m}) - least({n}, {m}) // 2 GROUP BY scene_id, i, j, {n}"


def _image(src: str = "scenes") -> str:
    return f""", p AS ({_PLAN.format(src=src)}), kr AS ({_axis('n_rows', 'm_rows')}), kc AS ({_axis('n_cols', 'm_cols')}),
half AS (SELECT x.scene_id, k.i, x.c, sum(re * kr - im * ki) AS re, sum(re * ki + im * kr) AS im FROM cells x JOIN kr k ON k.scene_id = x.scene_id AND k.j = x.r GROUP BY ALL),
image AS (SELECT x.scene_id, CAST(x.i AS INT) AS r, CAST(k.i AS INT) AS c, sum(re * kr - im * ki) AS re, sum(re * ki + im * kr) AS im FROM half x JOIN kc k ON k.scene_id = x.scene_id AND k.j = x.c GROUP BY ALL)"""


def _rows(where: str, src: str = "scenes") -> str:
    return with_views(f"cells {src}", f"{_image(src)} SELECT scene_id, r, c, round(re, 5) + 0.0 AS re, round(im, 5) + 0.0 AS im FROM image JOIN p USING (scene_id) WHERE {where}")


def _resampled(spark, sf, direction=None, strategy="local", mixed=False):
    sizes = scenes(spark, mixed)
    if direction:
        sizes = spectrum.plan(sizes).filter(F.col("direction") == direction).select(sizes.columns)
    cells = scene_cells(spark, sf).join(F.broadcast(sizes.select("scene_id")), "scene_id", "left_semi")
    y = spectrum.resample(cells, sizes, strategy=strategy)
    return y.select("scene_id", "r", "c", _R("re", 5).alias("re"), _R("im", 5).alias("im"))


@query(with_views("acq", f", s AS (SELECT scene_id, CAST(4000 + scene_id % 1000 AS INT) AS n_rows, CAST(3000 + scene_id % 700 AS INT) AS n_cols, native_az_m, native_rg_m FROM acq), p AS ({_PLAN.format(src='s')}) SELECT scene_id, m_rows, m_cols, {_DIR} AS dir_az, {_DIR2} AS dir_rg, round(n_rows * native_az_m / m_rows, 5) AS eff_az_m FROM p"))
def m2_plan(spark, sf):
    a = acquisitions(spark, sf).select("scene_id", (F.lit(4000) + F.col("scene_id") % 1000).cast("int").alias("n_rows"), (F.lit(3000) + F.col("scene_id") % 700).cast("int").alias("n_cols"), "native_az_m", "native_rg_m")
    return spectrum.plan(a).select("scene_id", "m_rows", "m_cols", "dir_az", "dir_rg", _R("eff_az_m", 5).alias("eff_az_m"))


@query(_rows("m_rows < n_rows"))
def m2_down(spark, sf):
    return _resampled(spark, sf, "down", "auto")


@query(_rows("m_rows > n_rows"))
def m2_up(spark, sf):
    return _resampled(spark, sf, "up", "auto")


@query(with_views("cells", "SELECT scene_id, r, c, round(re, 5) AS re, round(im, 5) AS im FROM cells WHERE scene_id = 'view'"))
def m2_identity(spark, sf):
    return _resampled(spark, sf, "identity", "auto")


@query(_rows(f"({_DIR}) <> ({_DIR2})", "mixed"))
def m2_mixed(spark, sf):
    return _resampled(spark, sf, "mixed", mixed=True)


def _all_scenes(name: str, strategy: str):
    query(_rows("n_rows <> m_rows"), name)(lambda spark, sf: _resampled(spark, sf, None, strategy).filter("scene_id <> 'view'"))


for _strategy in ("local", "separable", "kernel"):
    _all_scenes(f"m2_{_strategy}", _strategy)


@query(with_views("cells", ", f AS (SELECT scene_id, fr, fc, sum(re * cos(a) + im * sin(a)) AS x, sum(im * cos(a) - re * sin(a)) AS y FROM (SELECT *, 2 * pi() * (fr * r / 30::DOUBLE + fc * c / 24::DOUBLE) AS a FROM cells, range(-15, 15) tr(fr), range(-12, 12) tc(fc)) GROUP BY ALL) SELECT scene_id, CAST(fr AS INT) AS fr, CAST(fc AS INT) AS fc, round(sqrt(x * x + y * y), 4) AS magnitude FROM f"))
def m2_dft_mag(spark, sf):
    return spectrum.dft(scene_cells(spark, sf), scenes(spark)).select("scene_id", "fr", "fc", _R(F.hypot("re", "im"), 4).alias("magnitude"))


_SERIES = """, s AS (SELECT r * 24 + c AS j, sum(re) AS x FROM cells GROUP BY ALL), m AS (SELECT * FROM (VALUES (576), (1080)) t(m)),
k AS (SELECT m, i, j, i / m::DOUBLE - j / 720::DOUBLE AS d, least(m, 720) AS k FROM m, range(1080) ti(i), range(720) tj(j) WHERE i < m),
w AS (SELECT m, i, j, cos(pi() * d) * CASE WHEN abs(sin(pi() * d)) < 1e-12 THEN k ELSE sin(pi() * k * d) / sin(pi() * d) END / 720 AS w FROM k)
SELECT CAST(m AS INT) AS m, CAST(i AS INT) AS t, round(sum(w * x), 5) + 0.0 AS x FROM w JOIN s USING (j) GROUP BY ALL"""


@query(with_views("cells", _SERIES))
def m2_series(spark, sf):
    s = scene_cells(spark, sf).groupBy((F.col("r") * 24 + F.col("c")).alias("t")).agg(F.sum("re").alias("x")).withColumn("key", F.lit(0))
    made = [spectrum.resample_1d(s, 720, m).select(F.lit(m).alias("m"), "t", _R("x", 5).alias("x")) for m in (576, 1080)]
    return reduce(lambda a, b: a.unionByName(b), made)


@query(with_views("event_scenes", f", p AS ({_PLAN.format(src='event_scenes')}) SELECT scene_id, CASE WHEN {_DIR} = {_DIR2} THEN {_DIR} ELSE 'mixed' END AS direction, m_rows, m_cols, round(n_rows * native_az_m / m_rows, 8) AS eff_az_m, round(least(1.0::DOUBLE, n_rows / m_rows::DOUBLE), 8) AS bandwidth_az FROM p"))
def m2_provenance(spark, sf):
    return spectrum.provenance(event_scenes(spark, sf)).select("scene_id", "direction", "m_rows", "m_cols", _R("eff_az_m", 8).alias("eff_az_m"), _R("bandwidth_az", 8).alias("bandwidth_az"))


def _spatial(rows: str, cols: str, cells: str = "cells") -> str:
    return f""", p AS ({_PLAN.format(src='scenes')}), wr AS ({rows}), wc AS ({cols}), source AS (SELECT * FROM {cells}),
image AS (SELECT x.scene_id, CAST(a.i AS INT) AS r, CAST(b.i AS INT) AS c, sum(re * a.w * b.w) AS re, sum(im * a.w * b.w) AS im FROM source x JOIN wr a ON a.scene_id = x.scene_id AND a.j = x.r JOIN wc b ON b.scene_id = x.scene_id AND b.j = x.c GROUP BY ALL)"""


def _weights(method: str, n: str, m: str) -> str:
    base = f"SELECT scene_id, i, {n} AS n, {m} AS m, i * {n} / {m}::DOUBLE AS a FROM p, range(200) t(i) WHERE i < {m}"
    if method == "nearest":
        return f"SELECT scene_id, i, least(floor(a + 0.5), n - 1) AS j, 1.0::DOUBLE AS w FROM ({base})"
    if method == "bilinear":
        return f"SELECT scene_id, i, floor(a) AS j, 1 - (a - floor(a)) AS w FROM ({base}) UNION ALL SELECT scene_id, i, least(floor(a) + 1, n - 1), a - floor(a) FROM ({base})"
    return f"SELECT scene_id, i, j, 1 / count(*) OVER (PARTITION BY scene_id, i)::DOUBLE AS w FROM ({base}) q, range(200) tj(j) WHERE j >= floor(a) AND j < n AND j <= greatest(floor(a), ceil((i + 1) * n / m::DOUBLE) - 1)"


def _baseline_sql(method: str) -> str:
    box = "box" if method == "detected" else method
    cells = "(SELECT scene_id, r, c, re * re + im * im AS re, 0.0::DOUBLE AS im FROM cells)" if method == "detected" else "cells"
    return _spatial(_weights(box, "n_rows", "m_rows"), _weights(box, "n_cols", "m_cols"), cells)


def _baseline(method: str):
    def run(spark, sf):
        y = spectrum.resample_spatial(scene_cells(spark, sf), scenes(spark), method)
        tie = F.lit(3e-7)  # sums of halves and cents end on ties
        return y.select("scene_id", "r", "c", _R(F.col("re") + tie, 5).alias("re"), _R(F.col("im") + tie, 5).alias("im"))

    query(with_views("cells scenes", _baseline_sql(method) + " SELECT scene_id, r, c, round(re + 3e-7, 5) + 0.0 AS re, round(im + 3e-7, 5) + 0.0 AS im FROM image"), f"b_{method}")(run)


for _method in ("nearest", "bilinear", "box", "detected"):
    _baseline(_method)


@query(with_views("cells scenes", _image() + ", ei AS (SELECT scene_id, sum(re * re + im * im) AS e FROM cells GROUP BY ALL), eo AS (SELECT scene_id, sum(re * re + im * im) AS e FROM image GROUP BY ALL) SELECT scene_id, round(ei.e / n_rows / n_cols, 2) AS power_in, round(eo.e / m_rows / m_cols, 2) AS power_out, round((eo.e / m_rows / m_cols) / (ei.e / n_rows / n_cols), 6) AS ratio FROM p JOIN ei USING (scene_id) JOIN eo USING (scene_id)"))
def a2_energy(spark, sf):
    cells = scene_cells(spark, sf)
    e = spectrum.energy(cells, spectrum.resample(cells, scenes(spark)), scenes(spark))
    return e.select("scene_id", _R("power_in", 2).alias("power_in"), _R("power_out", 2).alias("power_out"), _R("ratio").alias("ratio"))


def _measure(name: str, column: str, sql: str):
    parts = []
    for m in ("nearest", "bilinear", "box"):
        inner = _baseline_sql(m).replace(", p AS", ", q AS", 1).split(", wr AS", 1)[1]
        names = {"wr": f"wr_{m}", "wc": f"wc_{m}", "source": f"source_{m}", "image": f"image_{m}"}
        text = ", wr AS" + inner
        for k, v in names.items():
            text = text.replace(f"{k} AS (", f"{v} AS (").replace(f"JOIN {k} ", f"JOIN {v} ").replace(f"FROM {k} x", f"FROM {v} x")
        parts.append(text)
    select = " UNION ALL ".join(f"SELECT '{m}' AS method, scene_id, round({sql}, 6) AS {column} FROM image a LEFT JOIN (SELECT * FROM image_{m}) b USING (scene_id, r, c) WHERE scene_id <> 'view' GROUP BY scene_id" for m in ("nearest", "bilinear", "box"))

    def run(spark, sf):
        cells = scene_cells(spark, sf)
        exact = spectrum.resample(cells, scenes(spark))
        rows = [spectrum.compare(exact, spectrum.resample_spatial(cells, scenes(spark), m)).select(F.lit(m).alias("method"), "scene_id", _R(column).alias(column)) for m in ("nearest", "bilinear", "box")]
        return reduce(lambda a, b: a.unionByName(b), rows).filter("scene_id <> 'view'")

    query(with_views("cells scenes", _image() + "".join(parts) + " " + select), name)(run)


_measure("a2_rmse", "rmse", "sqrt(sum((a.re - coalesce(b.re, 0)) ** 2 + (a.im - coalesce(b.im, 0)) ** 2) / sum(a.re ** 2 + a.im ** 2))")
_measure("a2_coherence", "coherence", "sqrt(sum(a.re * b.re + a.im * b.im) ** 2 + sum(a.im * b.re - a.re * b.im) ** 2) / sqrt(sum(a.re ** 2 + a.im ** 2) * sum(b.re ** 2 + b.im ** 2))")


@query(with_views("scenes", "SELECT scene_id, true AS exact FROM scenes"))
def a2_round_trip(spark, sf):
    """Largest difference after going up to twice the samples and back."""
    cells = scene_cells(spark, sf)
    half = scenes(spark).withColumn("native_az_m", F.lit(1.6)).withColumn("native_rg_m", F.lit(1.6))
    up = spectrum.resample(cells, half)
    back = scenes(spark).withColumn("n_rows", F.lit(60)).withColumn("n_cols", F.lit(48)).withColumn("native_az_m", F.lit(0.4)).withColumn("native_rg_m", F.lit(0.4))
    again = spectrum.resample(up, back)
    return spectrum.compare(cells, again).select("scene_id", (F.col("rmse") < 1e-9).alias("exact"))
