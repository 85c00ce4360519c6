"""Complex images as packed rows, the form for large corpora: 8 bytes a sample in one binary value.

A raster row is (scene_id, r0, c0, rows, cols, payload): a rectangle of an image in
little-endian interleaved complex numbers, line after line; `kind` "<c8" is the stored
form, "<c16" keeps doubles. Strips are whole lines, blocks are squares. Absent cells are
zero. Converters to and from cells (scene_id, r, c, re, im) serve SQL and small images.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from radarlake.methods import spectrum

BLOCK = 512


def schema(kind: str) -> str:
    return f"scene_id {kind}, r0 int, c0 int, rows int, cols int, payload binary"


def _scene(df: DataFrame) -> str:
    return dict(df.dtypes)["scene_id"]


def _rows(key: list, kind: pa.DataType, parts: list[tuple[int, int, np.ndarray]], dtype: str) -> pa.RecordBatch:
    """A batch of rectangles, each with the place of its first sample."""
    r0, c0, size = [p[0] for p in parts], [p[1] for p in parts], [p[2].shape for p in parts]
    payload = [np.ascontiguousarray(p[2]).astype(dtype).tobytes() for p in parts]
    columns = [pa.array(key, kind), *(pa.array(x, pa.int32()) for x in (r0, c0, [s[0] for s in size], [s[1] for s in size])), pa.array(payload, pa.binary())]
    return pa.RecordBatch.from_arrays(columns, names=["scene_id", "r0", "c0", "rows", "cols", "payload"])


def _image(payload, rows: int, cols: int, dtype: str) -> np.ndarray:
    return np.frombuffer(payload.as_buffer(), dtype).reshape(rows, cols)


def pack(cells: DataFrame, scenes: DataFrame, rows: int = BLOCK, cols: int | None = BLOCK, dtype: str = "<c8") -> DataFrame:
    """Cells as rectangles of up to rows by cols; `cols` None gives strips of whole lines. `scenes` has n_rows and n_cols."""

    def run(t: pa.Table) -> pa.Table:
        r0, c0, n, m = (t[k][0].as_py() for k in ("_r0", "_c0", "n_rows", "n_cols"))
        height, width = min(rows, n - r0), m if cols is None else min(cols, m - c0)
        x = np.zeros((height, width), complex)
        x[t["r"].to_numpy() - r0, t["c"].to_numpy() - c0] = t["re"].to_numpy() + 1j * t["im"].to_numpy()
        return pa.Table.from_batches([_rows([t["scene_id"][0].as_py()], t["scene_id"].type, [(r0, c0, x)], dtype)])

    start = lambda c, k: (F.floor(F.col(c) / k) * k).cast("int")
    placed = cells.join(scenes.select("scene_id", "n_rows", "n_cols"), "scene_id").withColumn("_r0", start("r", rows)).withColumn("_c0", F.lit(0) if cols is None else start("c", cols))
    return placed.groupBy("scene_id", "_r0", "_c0").applyInArrow(run, schema(_scene(cells)))


def unpack(raster: DataFrame, dtype: str = "<c8") -> DataFrame:
    """The cells of rectangles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            get = lambda n: b.column(b.schema.get_field_index(n))  # noqa: E731, B023
            for i in range(b.num_rows):
                x = _image(get("payload")[i], get("rows")[i].as_py(), get("cols")[i].as_py(), dtype)
                r, c = np.divmod(np.arange(x.size), max(x.shape[1], 1))
                key = pa.array([get("scene_id")[i].as_py()] * x.size, get("scene_id").type)
                places = [pa.array((v + get(k)[i].as_py()).astype(np.int32)) for v, k in ((r, "r0"), (c, "c0"))]
                yield pa.RecordBatch.from_arrays([key, *places, *(pa.array(np.ascontiguousarray(v).ravel().astype(np.float64)) for v in (x.real, x.imag))], names=["scene_id", "r", "c", "re", "im"])

    return raster.mapInArrow(run, f"scene_id {_scene(raster)}, r int, c int, re double, im double")


def resample(strips: DataFrame, scenes: DataFrame, target: float = spectrum.TARGET_M, block: int = BLOCK, dtype: str = "<c8") -> DataFrame:
    """Strips of whole lines at the target spacing, as blocks.

    Lines are transformed where they lie; their parts then go to blocks of columns in one
    exchange of packed values, and each block of columns is transformed from top to
    bottom. A task holds one block of columns, whatever the size of the scene.
    """
    kind = _scene(strips)
    sized = strips.join(spectrum.plan(scenes, target).select("scene_id", "n_rows", "n_cols", "m_rows", "m_cols"), "scene_id")

    def lines(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            get = lambda n: b.column(b.schema.get_field_index(n))  # noqa: E731, B023
            for i in range(b.num_rows):
                m = get("m_cols")[i].as_py()
                y = spectrum.resample_axis(_image(get("payload")[i], get("rows")[i].as_py(), get("cols")[i].as_py(), dtype).astype(complex), m, 1)
                parts = [(get("r0")[i].as_py(), c, y[:, c : c + block]) for c in range(0, m, block)]
                made = _rows([get("scene_id")[i].as_py()] * len(parts), get("scene_id").type, parts, dtype)
                sizes = [pa.array([get(n)[i].as_py()] * len(parts), pa.int32()) for n in ("n_rows", "m_rows")]
                yield pa.RecordBatch.from_arrays([*made.columns, *sizes], names=[*made.schema.names, "n_rows", "m_rows"])

    def columns(t: pa.Table) -> pa.Table:
        n, m, c0, width = (t[k][0].as_py() for k in ("n_rows", "m_rows", "c0", "cols"))
        x = np.zeros((n, width), complex)
        for r0, rows, payload in zip(t["r0"].to_pylist(), t["rows"].to_pylist(), t["payload"], strict=True):
            x[r0 : r0 + rows] = _image(payload, rows, width, dtype)
        y = spectrum.resample_axis(x, m, 0)
        parts = [(r, c0, y[r : r + block]) for r in range(0, m, block)]
        return pa.Table.from_batches([_rows([t["scene_id"][0].as_py()] * len(parts), t["scene_id"].type, parts, dtype)])

    dealt = sized.mapInArrow(lines, schema(kind) + ", n_rows int, m_rows int")
    return dealt.groupBy("scene_id", "c0").applyInArrow(columns, schema(kind))


def patches(blocks: DataFrame, rows: Column, cols: Column, stride: int = BLOCK, dtype: str = "<c8") -> DataFrame:
    """Patches of twice the stride from blocks of one stride: each block goes to the up to four patches that it is a quarter of.

    `rows` and `cols` are the image's sizes, columns of `blocks`. Patches that reach beyond the image are left out.
    """
    size, kind = 2 * stride, _scene(blocks)
    of = lambda c, n: F.filter(F.array(F.floor(F.col(c) / stride) - 1, F.floor(F.col(c) / stride)), lambda t: (t >= 0) & (t * stride + size <= n))
    placed = blocks.select("*", F.explode(of("r0", rows)).alias("tile_r")).select("*", F.explode(of("c0", cols)).alias("tile_c"))

    def run(t: pa.Table) -> pa.Table:
        i, j = t["tile_r"][0].as_py(), t["tile_c"][0].as_py()
        x = np.zeros((size, size), dtype)
        for r0, c0, h, w, payload in zip(*(t[k].to_pylist() for k in ("r0", "c0", "rows", "cols")), t["payload"], strict=True):
            r, c = r0 - i * stride, c0 - j * stride
            x[r : r + h, c : c + w] = _image(payload, h, w, dtype)[: size - r, : size - c]
        made = _rows([t["scene_id"][0].as_py()], t["scene_id"].type, [(i * stride, j * stride, x)], dtype)
        return pa.Table.from_batches([made]).append_column("tile_r", pa.array([i], pa.int64())).append_column("tile_c", pa.array([j], pa.int64()))

    return placed.groupBy("scene_id", "tile_r", "tile_c").applyInArrow(run, schema(kind) + ", tile_r long, tile_c long")
