"""Packed rasters against numpy, and strategies chosen scene by scene."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from radarlake.methods import raster, spectrum

SIZES = "scene_id string, n_rows int, n_cols int, native_az_m double, native_rg_m double"


def cells(spark, images):
    rows = [(k, i, j, float(x[i, j].real), float(x[i, j].imag)) for k, x in images.items() for i in range(x.shape[0]) for j in range(x.shape[1])]
    return spark.createDataFrame(rows, "scene_id string, r int, c int, re double, im double")


def images_of(df, shapes):
    out = {k: np.zeros(s, complex) for k, s in shapes.items()}
    for r in df.collect():
        out[r["scene_id"]][r["r"], r["c"]] = r["re"] + 1j * r["im"]
    return out


@pytest.fixture(scope="module")
def images():
    rng = np.random.default_rng(0)
    return {k: rng.normal(size=s) + 1j * rng.normal(size=s) for k, s in {"a": (13, 9), "b": (1, 20), "c": (16, 16), "d": (5, 1)}.items()}


@pytest.fixture(scope="module")
def scenes(spark, images):
    native = {"a": (0.5, 1.3), "b": (0.8, 0.4), "c": (0.8, 0.8), "d": (2.0, 0.8)}
    return spark.createDataFrame([(k, *x.shape, *native[k]) for k, x in images.items()], SIZES)


@pytest.mark.parametrize(("rows", "cols", "dtype", "near"), [(4, 4, "<c16", 0.0), (3, None, "<c16", 0.0), (7, 5, "<c8", 1e-6)])
def test_pack_and_unpack(spark, images, scenes, rows, cols, dtype, near):
    packed = raster.pack(cells(spark, images), scenes, rows, cols, dtype)
    for r in packed.collect():
        assert len(r["payload"]) == r["rows"] * r["cols"] * np.dtype(dtype).itemsize and r["rows"] <= rows
    back = images_of(raster.unpack(packed, dtype), {k: x.shape for k, x in images.items()})
    assert all(np.allclose(back[k], x, rtol=0, atol=near) for k, x in images.items())
    assert raster.unpack(packed.limit(0), dtype).count() == 0


@pytest.mark.parametrize(("lines", "block"), [(3, 4), (64, 64), (1, 1)])
def test_packed_resampling(spark, images, scenes, lines, block):
    sizes = {r["scene_id"]: (r["m_rows"], r["m_cols"]) for r in spectrum.plan(scenes).collect()}
    strips = raster.pack(cells(spark, images), scenes, lines, None, "<c16")
    got = images_of(raster.unpack(raster.resample(strips, scenes, block=block, dtype="<c16"), "<c16"), sizes)
    for k, x in images.items():
        want = spectrum.resample_axis(spectrum.resample_axis(x, sizes[k][0], 0), sizes[k][1], 1)
        assert np.allclose(got[k], want), k


def test_patches_of_blocks(spark, images, scenes):
    blocks = raster.pack(cells(spark, images), scenes, 4, 4, "<c16").join(scenes.select("scene_id", "n_rows", "n_cols"), "scene_id")
    rows = raster.patches(blocks, F.col("n_rows"), F.col("n_cols"), 4, "<c16").collect()
    want = {(k, i, j) for k, x in images.items() for i in range(9) for j in range(9) if i * 4 + 8 <= x.shape[0] and j * 4 + 8 <= x.shape[1]}
    assert {(r["scene_id"], r["tile_r"], r["tile_c"]) for r in rows} == want and len(rows) == len(want) == 2 + 9
    for r in rows:
        part = images[r["scene_id"]][r["r0"] : r["r0"] + 8, r["c0"] : r["c0"] + 8]
        assert np.allclose(np.frombuffer(bytes(r["payload"]), "<c16").reshape(8, 8), part)


def test_strategy_is_chosen_scene_by_scene(spark, images, scenes, monkeypatch):
    """A budget that only the small scenes meet: the large one goes separably, and all images are the same."""
    sizes = {r["scene_id"]: (r["m_rows"], r["m_cols"]) for r in spectrum.plan(scenes).collect()}
    df = cells(spark, images)
    whole = images_of(spectrum.resample(df, scenes), sizes)
    monkeypatch.setattr(spectrum, "TASK_BYTES", 3 * 16 * 60)
    plan = spectrum.resample(df, scenes)
    got = images_of(plan, sizes)
    assert all(np.allclose(got[k], whole[k]) for k in images)


@pytest.mark.parametrize("method", ["nearest", "bilinear", "box"])
def test_spatial_weights_against_plain_loops(spark, images, scenes, method):
    sizes = {r["scene_id"]: (r["m_rows"], r["m_cols"]) for r in spectrum.plan(scenes).collect()}

    def axis(n, m):
        w = np.zeros((m, n))
        for i in range(m):
            a = i * n / m
            low = int(np.floor(a))
            if method == "nearest":
                w[i, min(int(np.floor(a + 0.5)), n - 1)] += 1
            elif method == "bilinear":
                w[i, low] += 1 - (a - low)
                w[i, min(low + 1, n - 1)] += a - low
            else:
                high = min(max(low, int(np.ceil((i + 1) * n / m)) - 1), n - 1)
                w[i, low : high + 1] = 1 / (high - low + 1)
        return w

    got = images_of(spectrum.resample_spatial(cells(spark, images), scenes, method), sizes)
    for k, x in images.items():
        m = sizes[k]
        assert np.allclose(got[k], axis(x.shape[0], m[0]) @ x @ axis(x.shape[1], m[1]).T), (k, method)
