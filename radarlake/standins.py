"""Views of the given tables that stand for the corpus: scenes, cells, patches, tiles, captions.

Each view has a DuckDB twin in `SQL`, a named subquery for `with_views`.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TARGET_M = 0.8
#: Native spacing of the five event scenes, in metres.
NATIVE_M = {"click": 0.5, "error": 0.6, "view": 0.8, "signup": 1.25, "purchase": 2.0}
#: The same with another spacing across range, so that axes differ.
MIXED_RG_M = {"click": 1.25, "error": 2.0, "view": 0.5, "signup": 0.5, "purchase": 0.6}
ROWS, COLS = 30, 24


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def acquisitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per scene; the scene is also the pass."""
    t = lambda n: table(spark, sf_dir, n)
    rank = F.substring("o_orderpriority", 1, 1)
    return (
        t("orders")
        .join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
        .join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey"))
        .join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
        .select(
            F.col("o_orderkey").alias("scene_id"), F.col("o_custkey").alias("city_id"), F.col("n_name").alias("country"), F.col("r_name").alias("continent"),
            F.when(rank.isin("1", "3"), "VV").when(rank.isin("2", "4"), "HH").otherwise("HV").alias("pol"),
            (F.lit(0.15) + F.col("o_totalprice") / 250000).alias("native_az_m"),
            (F.lit(0.15) + (F.col("o_orderkey") * 37 % 211) / F.lit(100.0)).alias("native_rg_m"),
            (F.lit(5) + F.col("o_custkey") * 7 % 71).cast("int").alias("incidence_deg"),
            (F.col("o_custkey") * 13 % 161 - 80).cast("double").alias("lat0"), (F.col("o_custkey") * 29 % 360 - 180).cast("double").alias("lon0"),
            F.col("o_orderdate").alias("acquired_on"),
        )
    )


def samples_fact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per patch."""
    return table(spark, sf_dir, "lineitem").join(acquisitions(spark, sf_dir), F.col("l_orderkey") == F.col("scene_id"))


def scene_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five complex images of 30 days by 24 hours; absent cells are zero."""
    day = F.datediff(F.col("ts"), F.lit("2024-01-01").cast("date"))
    return (
        table(spark, sf_dir, "events")
        .select(F.col("event_type").alias("scene_id"), day.alias("r"), F.hour("ts").alias("c"), "value", F.get_json_object("props", "$.k").cast("int").alias("k"))
        .filter(F.col("r").between(0, ROWS - 1))
        .groupBy("scene_id", "r", "c")
        .agg(F.sum("value").alias("re"), F.sum("k").cast("double").alias("im"))
    )


def scenes(spark: SparkSession, mixed: bool = False) -> DataFrame:
    """Sizes and native spacings of the event scenes."""
    rows = [(k, ROWS, COLS, v, MIXED_RG_M[k] if mixed else v) for k, v in NATIVE_M.items()]
    return spark.createDataFrame(rows, "scene_id string, n_rows int, n_cols int, native_az_m double, native_rg_m double")


def event_scenes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The event scenes in the sizes that their cells reach."""
    reach = scene_cells(spark, sf_dir).groupBy("scene_id").agg((F.max("r") + 1).alias("n_rows"), (F.max("c") + 1).alias("n_cols"))
    return reach.join(F.broadcast(scenes(spark).drop("n_rows", "n_cols")), "scene_id")


def vec_patches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """8 x 8 complex patches with a class, in long form."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("patch_id"), "label", "embedding", F.posexplode("embedding").alias("p", "re"))
    other = F.element_at("embedding", (F.col("p") + 32) % 64 + 1)
    return e.select("patch_id", "label", F.floor(F.col("p") / 8).cast("int").alias("r"), (F.col("p") % 8).cast("int").alias("c"), F.col("re").cast("double").alias("re"), other.cast("double").alias("im"))


def optical_tiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """8 x 8 tiles of three bands, 0 to 255, in long form (tile_id, band, v, u, value)."""
    e = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    n = e.agg(F.count("*").alias("n"))
    bands = e.crossJoin(F.broadcast(n)).select(F.explode(F.array(*(F.struct(F.pmod(F.col("vec_id") - b, F.col("n")).alias("tile_id"), F.lit(b).alias("band")) for b in range(3)))).alias("s"), "embedding")
    cell = bands.select("s.tile_id", "s.band", F.posexplode("embedding").alias("p", "x"))
    return cell.select("tile_id", "band", F.floor(F.col("p") / 8).cast("int").alias("v"), (F.col("p") % 8).cast("int").alias("u"), (F.col("x").cast("double") * 127.5 + 127.5).alias("value"))


def captions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three captions of each document: its first words."""
    from radarlake.methods import caption

    lengths = {"SHORT": (12, 7), "MID": (20, 13), "LONG": (27, 23)}
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("sample_id"), "text")
    return caption.long(caption.generate(docs, lambda text, variant: caption.first_words(text, F.lit(lengths[variant][0]) + F.col("sample_id") % lengths[variant][1], sum(lengths[variant]) - 1)))


#: DuckDB text of the views.
SQL = {
    "acq": """SELECT o_orderkey AS scene_id, o_custkey AS city_id, n_name AS country, r_name AS continent,
      CASE WHEN substr(o_orderpriority, 1, 1) IN ('1', '3') THEN 'VV' WHEN substr(o_orderpriority, 1, 1) IN ('2', '4') THEN 'HH' ELSE 'HV' END AS pol,
      0.15::DOUBLE + o_totalprice / 250000 AS native_az_m, 0.15::DOUBLE + (o_orderkey * 37 % 211) / 100.0::DOUBLE AS native_rg_m,
      CAST(5 + o_custkey * 7 % 71 AS INT) AS incidence_deg, CAST(o_custkey * 13 % 161 - 80 AS DOUBLE) AS lat0, CAST(o_custkey * 29 % 360 - 180 AS DOUBLE) AS lon0, o_orderdate AS acquired_on
      FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey""",
    "fact": "SELECT * FROM lineitem JOIN acq ON l_orderkey = scene_id",
    "cells": """SELECT event_type AS scene_id, CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INT) AS r, CAST(hour(ts) AS INT) AS c, sum(value) AS re, CAST(sum(CAST(json_extract_string(props, '$.k') AS INT)) AS DOUBLE) AS im
      FROM events WHERE date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) BETWEEN 0 AND 29 GROUP BY ALL""",
    "scenes": f"SELECT * FROM (VALUES {', '.join(f"('{k}', 30, 24, {v}::DOUBLE, {v}::DOUBLE)" for k, v in NATIVE_M.items())}) t(scene_id, n_rows, n_cols, native_az_m, native_rg_m)",
    "mixed": f"SELECT * FROM (VALUES {', '.join(f"('{k}', 30, 24, {v}::DOUBLE, {MIXED_RG_M[k]}::DOUBLE)" for k, v in NATIVE_M.items())}) t(scene_id, n_rows, n_cols, native_az_m, native_rg_m)",
    "event_scenes": "SELECT scene_id, CAST(max(r) + 1 AS INT) AS n_rows, CAST(max(c) + 1 AS INT) AS n_cols, native_az_m, native_rg_m FROM cells JOIN (SELECT scene_id, native_az_m, native_rg_m FROM scenes) s USING (scene_id) GROUP BY ALL",
    "patches": """SELECT vec_id AS patch_id, label, CAST(p // 8 AS INT) AS r, CAST(p % 8 AS INT) AS c, CAST(embedding[p + 1] AS DOUBLE) AS re, CAST(embedding[(p + 32) % 64 + 1] AS DOUBLE) AS im
      FROM embeddings, range(64) t(p)""",
    "optical": """SELECT (vec_id - b + n) % n AS tile_id, CAST(b AS INT) AS band, CAST(p // 8 AS INT) AS v, CAST(p % 8 AS INT) AS u, CAST(embedding[p + 1] AS DOUBLE) * 127.5 + 127.5 AS value
      FROM embeddings, (SELECT count(*) AS n FROM embeddings), range(3) tb(b), range(64) tp(p)""",
    "words": r"SELECT doc_id AS sample_id, regexp_split_to_array(regexp_replace(text, '^\s+|\s+$', '', 'g'), '\s+') AS w FROM documents",
    "captions": """SELECT sample_id, variant, array_to_string(w[1:CASE variant WHEN 'SHORT' THEN 12 + sample_id % 7 WHEN 'MID' THEN 20 + sample_id % 13 ELSE 27 + sample_id % 23 END], ' ') AS text
      FROM words, (VALUES ('SHORT'), ('MID'), ('LONG')) t(variant)""",
}
_NEEDS = {"fact": ["acq"], "event_scenes": ["cells", "scenes"], "captions": ["words"]}


def with_views(names: str, body: str) -> str:
    """`body` with the named views in front; `body` may begin with more of them after a comma."""
    listed: list[str] = []
    for n in names.split():
        for m in (*_NEEDS.get(n, []), n):
            if m not in listed:
                listed.append(m)
    views = ", ".join(f"{n} AS ({SQL[n]})" for n in listed)
    return f"WITH RECURSIVE {views} {body}"
