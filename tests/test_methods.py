"""Worked examples and invariants of the corpus methods."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from radarlake.methods import align, caption, geo, pairing, release, select, spectrum, tiling


def image(spark, x, scene="s"):
    n, m = x.shape
    rows = [(scene, i, j, float(x[i, j].real), float(x[i, j].imag)) for i in range(n) for j in range(m)]
    return spark.createDataFrame(rows, "scene_id string, r int, c int, re double, im double")


def back(df, n, m):
    y = np.zeros((n, m), complex)
    for r in df.collect():
        y[r["r"], r["c"]] = r["re"] + 1j * r["im"]
    return y


@pytest.mark.parametrize(("n", "m"), [(24, 18), (24, 36), (25, 18), (25, 36), (24, 17), (30, 75), (1, 3), (5, 1)])
def test_axis_keeps_constants_and_round_trips(n, m):
    rng = np.random.default_rng(n * 100 + m)
    assert np.allclose(spectrum.resample_axis(np.ones(n), m, 0), 1)
    x = rng.normal(size=n) + 1j * rng.normal(size=n)
    y = spectrum.resample_axis(x, m, 0)
    if m >= n:
        assert np.allclose(spectrum.resample_axis(y, n, 0), x)
        assert np.isclose((abs(y) ** 2).mean(), (abs(x) ** 2).mean())
    tone = np.exp(2j * np.pi * 0 * np.arange(n) / n)
    assert np.allclose(spectrum.resample_axis(tone, m, 0), 1)


@pytest.mark.parametrize(("native", "m"), [(0.5, 8), (0.8, 12), (1.25, 19)])
def test_strategies_agree(spark, native, m):
    rng = np.random.default_rng(1)
    x = rng.normal(size=(12, 12)) + 1j * rng.normal(size=(12, 12))
    sizes = spark.createDataFrame([("s", 12, 12, native, 0.8)], "scene_id string, n_rows int, n_cols int, native_az_m double, native_rg_m double")
    want = spectrum.resample_axis(x, m, 0)
    for strategy in ("local", "separable", "kernel", "auto"):
        got = back(spectrum.resample(image(spark, x), sizes, strategy=strategy, block=5), m, 12)
        assert np.allclose(got, want), strategy


def test_geodetic_round_trip_and_poles(spark):
    rows = [(lat, lon, h) for lat in (-89.9, -45.0, 0.0, 12.5, 89.9) for lon in (-180.0, 0.0, 179.9) for h in (-400.0, 0.0, 9000.0)]
    df = spark.createDataFrame(rows, "lat double, lon double, h double")
    x = geo.llh_to_ecef(F.col("lat"), F.col("lon"), F.col("h"))
    at = df.select("lat", "h", *(c.alias(k) for c, k in zip(x, "xyz")))
    out = at.select("lat", "h", *(c.alias(k) for c, k in zip(geo.ecef_to_llh(F.col("x"), F.col("y"), F.col("z")), ("lat2", "lon2", "h2"))))
    for r in out.collect():
        assert abs(r["lat"] - r["lat2"]) < 1e-9 and abs(r["h"] - r["h2"]) < 1e-4


def test_range_doppler_finds_planted_points():
    truth = np.array([[geo.A, 0.0, 0.0], [geo.A * math.cos(0.01), geo.A * math.sin(0.01), 0.0]])
    sensor = np.array([[geo.A + 500e3, -400e3, 100e3]] * 2)
    velocity = np.array([[0.0, 100.0, 7500.0]] * 2)
    d = truth - sensor
    rng = np.linalg.norm(d, axis=1)
    cone = (d * velocity).sum(1) / np.linalg.norm(velocity, axis=1) / rng
    got, left = geo.rdoppler_to_ecef(sensor, velocity, rng, cone, truth + 2000.0, rounds=8)
    assert np.allclose(got, truth, atol=1e-3) and (left < 1e-3).all()


@pytest.mark.parametrize(("extent", "count"), [(1024, 1), (1536, 2), (1535, 1), (1023, 0)])
def test_tile_counts(spark, extent, count):
    df = spark.createDataFrame([(extent, 1024)], "m_rows int, m_cols int")
    assert tiling.index(df).count() == count
    covered = {r["row0"] for r in tiling.index(df, edge="pad").collect()}
    assert max(covered) + 1024 >= extent


def test_interior_cells_lie_in_four_patches(spark):
    cells = image(spark, np.ones((16, 16), complex))
    tiles = tiling.explode_cells(cells, 8, 4, F.lit(16), F.lit(16))
    n = {(r["r"], r["c"]): r["n"] for r in tiles.groupBy("r", "c").agg(F.count("*").alias("n")).collect()}
    assert n[8, 8] == 4 and n[0, 0] == 1 and len(n) == 256
    assert tiles.select("tile_r", "tile_c", "y", "x").distinct().count() == tiling.from_blocks(cells, 4, F.lit(16), F.lit(16)).count() == 9 * 64


def test_cover_across_the_date_line(spark):
    box = spark.createDataFrame([(0.1, 0.2, 179.0, -179.0)], "south double, north double, west double, east double")
    xs = {r["x"] for r in pairing.tile_cover(box, 8).collect()}
    assert xs == {255, 0}


def test_affine_recovers_a_planted_map(spark):
    f = lambda x, y: (2.0 * x - y + 3, 0.5 * x + 1.5 * y - 1)
    points = [(F.lit(float(x)), F.lit(float(y)), *(F.lit(v) for v in f(x, y))) for x, y in ((0, 0), (1023, 0), (0, 1023), (1023, 1023))]
    row = spark.range(1).withColumn("a", align.fit(points)).withColumn("b", align.invert(F.col("a"))).first()
    assert np.allclose([row["a"][k] for k in align.FIELDS], [2, -1, 3, 0.5, 1.5, -1])
    assert np.isclose(row["b"]["a11"], 1.5 / 3.5)
    flat = [(F.lit(float(x)), F.lit(2.0 * x), F.lit(0.0), F.lit(0.0)) for x in range(3)]
    assert spark.range(1).withColumn("a", align.fit(flat)).first()["a"] is None


def test_bilinear_sampling_and_its_edges(spark):
    df = spark.createDataFrame([(0, [[1.0, 2.0], [3.0, 4.0]])], "tile_id int, image array<array<double>>")
    for (u, v), want, inside in [((0.5, 0.5), 2.5, True), ((1.0, 1.0), 4.0, True), ((1.01, 1.0), 0.0, False), ((-0.01, 0.0), 0.0, False)]:
        got = align.warp(df.withColumn("pu", F.lit(u)).withColumn("pv", F.lit(v)), "image", 2, 2).first()
        assert abs(got["value"] - want) < 1e-12 and got["inside"] == inside


def test_cleaning_is_idempotent_and_labels_follow_words(spark):
    texts = [("A  red and blue roof , possibly a factory",), ("an airport with a runway",), ("ports and a pier",), ("no port here",), ("",), (None,)]
    df = spark.createDataFrame(texts, "text string").withColumn("once", caption.clean(F.col("text"))).withColumn("twice", caption.clean(F.col("once")))
    rows = df.collect()
    assert rows[0]["once"] == "A roof, a factory."
    assert all(r["once"] == r["twice"] for r in rows)
    labels = [r["category"] for r in caption.label(df.select("text")).collect()]
    assert labels == ["industrial", "airport", "port", "other", "other", "other"]


def test_caption_statistics_by_hand(spark):
    rows = [("S", t) for t in ("a b", "a b", "c d e", "f", "g h", "a c")]
    df = spark.createDataFrame(rows, "variant string, text string")
    d = caption.duplicates(df).first()
    assert np.isclose(d["dup_extra"], 1 / 6) and np.isclose(d["dup_member"], 2 / 6)
    assert caption.vocabulary(df).first()["vocabulary"] == 8
    assert np.isclose(caption.stats(df).first()["mean_words"], 12 / 6)


def test_split_isolates_passes(spark):
    df = spark.range(2000).withColumn("pass", F.col("id") % 300)
    s = release.split(df, "pass")
    assert release.leakage(s, "pass").first()["leaking"] == 0
    assert release.leakage(release.split_random(df, "id"), "pass").first()["leaking"] > 0


def test_selection_rejects_nulls(spark):
    df = spark.createDataFrame([("VV", 30, 0.5, 0.5), (None, 30, 0.5, 0.5), ("HV", 30, 0.5, 0.5), ("HH", 9, 0.5, 0.5)], "pol string, incidence_deg int, native_az_m double, native_rg_m double")
    assert select.scenes(df).count() == 1 and select.audit(df).first()["kept"] == 1
