"""From pixels of the slant plane to places on the WGS84 ellipsoid, as Column expressions.

Grids are expressions and never stored: per-pixel coordinates would be six times the
complex samples. Angles are degrees, lengths metres.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: WGS84, fixed values.
A = 6378137.0
FLATTENING = 1 / 298.257223563
B = A * (1 - FLATTENING)
E2 = FLATTENING * (2 - FLATTENING)
EP2 = E2 / (1 - E2)

Vec = tuple[Column, Column, Column]


def llh_to_ecef(lat: Column, lon: Column, h: Column) -> Vec:
    p, q = F.radians(lat), F.radians(lon)
    n = A / F.sqrt(1 - E2 * F.sin(p) * F.sin(p))
    return (n + h) * F.cos(p) * F.cos(q), (n + h) * F.cos(p) * F.sin(q), (n * (1 - E2) + h) * F.sin(p)


def ecef_to_llh(x: Column, y: Column, z: Column, rounds: int = 2) -> Vec:
    """Fixed rounds of the parametric-latitude iteration: codegen without a loop, stable at the poles."""
    p = F.hypot(x, y)
    theta = F.atan2(z * A, p * B)
    phi = theta
    for _ in range(rounds):
        s, c = F.sin(theta), F.cos(theta)
        phi = F.atan2(z + EP2 * B * s * s * s, p - E2 * A * c * c * c)
        theta = F.atan2((1 - FLATTENING) * F.sin(phi), F.cos(phi))
    h = p * F.cos(phi) + z * F.sin(phi) - A * F.sqrt(1 - E2 * F.sin(phi) * F.sin(phi))
    return F.degrees(phi), F.degrees(F.atan2(y, x)), h


def frame(lat: Column, lon: Column) -> tuple[Vec, Vec, Vec]:
    """Unit vectors east, north, up."""
    p, q = F.radians(lat), F.radians(lon)
    zero = F.lit(0.0)
    return (-F.sin(q), F.cos(q), zero), (-F.sin(p) * F.cos(q), -F.sin(p) * F.sin(q), F.cos(p)), (F.cos(p) * F.cos(q), F.cos(p) * F.sin(q), F.sin(p))


def slant_axes(lat: Column, lon: Column, incidence: Column) -> tuple[Vec, Vec]:
    """Unit vectors along azimuth (north) and along slant range (east, tilted down by the incidence)."""
    east, north, up = frame(lat, lon)
    t = F.radians(incidence)
    return north, tuple(F.sin(t) * e - F.cos(t) * u for e, u in zip(east, up, strict=True))


def dot(a: Vec, b: Vec) -> Column:
    return a[0] * b[0] + a[1] * b[1] + a[2] * b[2]


def cross(a: Vec, b: Vec) -> Vec:
    return a[1] * b[2] - a[2] * b[1], a[2] * b[0] - a[0] * b[2], a[0] * b[1] - a[1] * b[0]


def plane_to_ecef(scp: Vec, u_az: Vec, u_rg: Vec, az_m: Column, rg_m: Column, up: Vec | None = None) -> Vec:
    """Scene centre plus offsets along the plane's axes; with `up`, slid along the plane's normal to the tangent plane."""
    step = tuple(az_m * a + rg_m * r for a, r in zip(u_az, u_rg, strict=True))
    if up is not None:
        normal = cross(u_az, u_rg)
        slide = F.try_divide(dot(step, up), dot(normal, up))
        step = tuple(s - slide * n for s, n in zip(step, normal, strict=True))
    return tuple(c + s for c, s in zip(scp, step, strict=True))


def image_grid(df: DataFrame, rows: str = "m_rows", cols: str = "m_cols") -> DataFrame:
    """Every pixel with its offset from the scene centre, in metres and in samples of the native grid."""
    r = df.withColumn("r", F.explode(F.sequence(F.lit(0), F.col(rows) - 1)))
    px = r.withColumn("c", F.explode(F.sequence(F.lit(0), F.col(cols) - 1)))
    centre = lambda n, m: (F.floor(F.col(n) / 2) * F.col(m) / F.col(n))
    row, col = F.col("r") - centre("n_rows", rows), F.col("c") - centre("n_cols", cols)
    return px.withColumn("native_row", row * F.col("n_rows") / F.col(rows)).withColumn("native_col", col * F.col("n_cols") / F.col(cols)).withColumn("az_m", row * F.col("eff_az_m")).withColumn("rg_m", col * F.col("eff_rg_m"))


def bound(values: dict[str, Column], f) -> Column:
    """`f` of a struct of the values, each built once however often `f` names it."""
    return F.transform(F.array(F.struct(*(v.alias(k) for k, v in values.items()))), f)[0]


def pixel_llh(az_m: Column, rg_m: Column, ground: bool = True) -> Column:
    """Struct (lat, lon, h) of an offset in a scene with lat0, lon0, incidence_deg."""
    lat, lon = F.col("lat0"), F.col("lon0")
    u_az, u_rg = slant_axes(lat, lon, F.col("incidence_deg"))
    at = plane_to_ecef(llh_to_ecef(lat, lon, F.lit(0.0)), u_az, u_rg, az_m, rg_m, frame(lat, lon)[2] if ground else None)

    def latitude(v: Column) -> Column:
        s, c = F.sin(v["t"]), F.cos(v["t"])
        return F.atan2(v["z"] + EP2 * B * s * s * s, v["p"] - E2 * A * c * c * c)

    def geodetic(v: Column) -> Column:
        phi = latitude(v)
        end = lambda w: F.struct(F.degrees(w["f"]).alias("lat"), F.degrees(F.atan2(v["y"], v["x"])).alias("lon"), (v["p"] * F.cos(w["f"]) + v["z"] * F.sin(w["f"]) - A * F.sqrt(1 - E2 * F.sin(w["f"]) * F.sin(w["f"]))).alias("h"))
        return bound({"f": phi}, end)

    def again(v: Column) -> Column:
        theta = bound({"f": latitude(v)}, lambda w: F.atan2((1 - FLATTENING) * F.sin(w["f"]), F.cos(w["f"])))
        return bound({"x": v["x"], "y": v["y"], "z": v["z"], "p": v["p"], "t": theta}, geodetic)

    def begin(v: Column) -> Column:
        p = F.hypot(v["x"], v["y"])
        return bound({"x": v["x"], "y": v["y"], "z": v["z"], "p": p, "t": F.atan2(v["z"] * A, p * B)}, again)

    return bound(dict(zip("xyz", at, strict=True)), begin)


def patch_bbox(df: DataFrame, az0: Column, az1: Column, rg0: Column, rg1: Column) -> DataFrame:
    """Boxes of a patch in latitude and longitude, from its four corners; across 180 degrees `west` exceeds `east`.

    The corners are an array column of their own, so that the projection is built and run once.
    """
    offsets = F.array(*(F.struct(a.alias("az"), r.alias("rg")) for a in (az0, az1) for r in (rg0, rg1)))

    at = df.withColumn("_corners", F.transform(offsets, lambda p: pixel_llh(p["az"], p["rg"])))
    lat, lon = F.transform("_corners", lambda p: p["lat"]), F.transform("_corners", lambda p: p["lon"])
    shifted = F.transform("_corners", lambda p: F.when(p["lon"] < 0, p["lon"] + 360).otherwise(p["lon"]))
    wide = F.array_max(lon) - F.array_min(lon) > 180
    back = lambda x: F.when(x > 180, x - 360).otherwise(x)
    return at.withColumns({
        "south": F.array_min(lat), "north": F.array_max(lat),
        "west": F.when(wide, back(F.array_min(shifted))).otherwise(F.array_min(lon)), "east": F.when(wide, back(F.array_max(shifted))).otherwise(F.array_max(lon)),
        "wraps": wide,
    }).drop("_corners")


def wrap_bbox(west: Column, east: Column) -> Column:
    """A box as one range of longitudes, or two if it crosses 180 degrees."""
    two = F.array(F.struct(west.alias("west"), F.lit(180.0).alias("east")), F.struct(F.lit(-180.0).alias("west"), east.alias("east")))
    return F.when(west > east, two).otherwise(F.array(F.struct(west.alias("west"), east.alias("east"))))


def ground_extent(slant_m: Column, incidence: Column) -> Column:
    return F.try_divide(slant_m, F.sin(F.radians(incidence)))


def incidence(kind: str, slope_deg: Column | None = None, product: Column | None = None) -> Column:
    """Incidence angle: `ellipsoid` from the look vector and the ellipsoid's up, `terrain` less the slope, `product` as stated, else the first known."""
    lat, lon = F.col("lat0"), F.col("lon0")
    _, look = slant_axes(lat, lon, F.col("incidence_deg"))
    plain = F.degrees(F.acos(-dot(look, frame(lat, lon)[2])))
    if kind == "ellipsoid":
        return plain
    terrain = plain - slope_deg if slope_deg is not None else F.lit(None).cast("double")
    stated = product if product is not None else F.lit(None).cast("double")
    return {"terrain": terrain, "product": stated, "any": F.coalesce(stated, terrain, plain)}[kind]


def rdoppler_to_ecef(sensor: np.ndarray, velocity: np.ndarray, rng: np.ndarray, cos_cone: np.ndarray, start: np.ndarray, h0: float = 0.0, rounds: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Points on the surface of height h0 at a range and Doppler cone, by Newton steps for many pixels at once; also the residuals in metres.

    Unknowns are three coordinates; the equations are range, cone and the ellipsoid
    enlarged by h0. numpy: called from a batch function.
    """
    p, speed = start.astype(float).copy(), np.linalg.norm(velocity, axis=1)
    axes = np.array([A + h0, A + h0, B + h0])
    for step in range(rounds + 1):
        d = p - sensor
        f = np.stack([np.linalg.norm(d, axis=1) - rng, (d * velocity).sum(1) / speed - rng * cos_cone, ((p / axes) ** 2).sum(1) * A / 2 - A / 2], 1)
        if step == rounds:
            return p, np.abs(f).max(1)
        jacobian = np.stack([d / np.linalg.norm(d, axis=1)[:, None], velocity / speed[:, None], p / axes**2 * A], 1)
        p -= np.linalg.solve(jacobian, f[:, :, None])[:, :, 0]
    raise AssertionError


def rdoppler(df: DataFrame, h0: float = 0.0, rounds: int = 5) -> DataFrame:
    """Rows (sensor, velocity, start: arrays of three; rng, cos_cone) with the point `at` they image on the surface of height h0, and the residual in metres."""

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            vec = lambda n: b.column(b.schema.get_field_index(n)).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, 3)  # noqa: E731, B023
            one = lambda n: b.column(b.schema.get_field_index(n)).to_numpy(zero_copy_only=False)  # noqa: E731, B023
            p, rest = rdoppler_to_ecef(vec("sensor"), vec("velocity"), one("rng"), one("cos_cone"), vec("start"), h0, rounds)
            at = pa.ListArray.from_arrays(pa.array(np.arange(len(p) + 1, dtype=np.int32) * 3), pa.array(p.ravel()))
            yield pa.RecordBatch.from_arrays([*b.columns, at, pa.array(rest)], names=[*b.schema.names, "at", "residual"])

    schema = ", ".join(f"`{c}` {t}" for c, t in df.dtypes)
    return df.mapInArrow(run, f"{schema}, at array<double>, residual double")


def metres_apart(a: Vec, b: Vec) -> Column:
    return F.sqrt(sum(((x - y) * (x - y) for x, y in zip(a, b, strict=True)), F.lit(0.0)))


RADIANS = math.pi / 180
