"""What grows with the input: what is broadcast, and odd inputs of the queries changed for it."""

from datetime import datetime, timedelta

import pytest
from pyspark.sql import functions as F

from radarlake import registry
from test_whole import _against_twin, _same, _whole


def _children(node):
    if node.getClass().getSimpleName() == "AdaptiveSparkPlanExec":
        return [node.executedPlan()]
    if node.getClass().getSimpleName().endswith("QueryStageExec"):
        return [node.plan()]
    return [node.children().apply(i) for i in range(node.children().size())]


def _most_broadcast(df):
    """Rows of the largest broadcast in the plan that ran."""
    df.collect()
    most, rest = 0, [df._jdf.queryExecution().executedPlan()]
    while rest:
        node = rest.pop()
        if node.getClass().getSimpleName() == "BroadcastExchangeExec":
            most = max(most, node.metrics().get("numOutputRows").get().value())
        rest += _children(node)
    return most


@pytest.mark.parametrize("name", ["m6_warp_join", "m6_warp", "m8_reconstruct", "b_reverse", "a6_refit"])
def test_pixels_are_not_broadcast(spark, sf, name):
    tiles = spark.read.parquet(f"{sf}/embeddings.parquet").count()
    assert _most_broadcast(registry.queries()[name](spark, sf)) <= tiles
    _against_twin(spark, sf, name)


def test_range_of_seconds_rounds(spark, tmp_path):
    """A time counts to its nearest second, halves to the even one, so 0.4 s and 3600.6 s lie over an hour apart."""
    begin, at = datetime(2024, 1, 1), [0.4, 3600.6, 8000.5, 11601.5, 20000.0, 23600.4]
    rows = [(i, begin + timedelta(seconds=s), 1, "click", float(2**i), "{}") for i, s in enumerate(at)]
    spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string").write.parquet(f"{tmp_path}/events.parquet")
    got = dict(registry.queries()["op_win_range"](spark, str(tmp_path)).collect())
    import duckdb

    db = duckdb.connect()
    db.sql(f"create view events as select * from '{tmp_path}/events.parquet/*.parquet'")
    assert got == dict(db.sql(registry.oracles()["op_win_range"]).fetchall())
    assert got == {0: 1.0, 1: 2.0, 2: 4.0, 3: 8.0, 4: 16.0, 5: 48.0}


def test_nearest_other_date(spark):
    """Against all pairs: crowded days, places of one row, ids that occur again, rows without a date."""
    import random

    import duckdb

    from radarlake.methods import pairing

    draw = random.Random(5)
    days = [datetime(2024, 1, 1) + timedelta(days=draw.randint(0, 40), hours=draw.randint(0, 2)) for _ in range(400)]
    rows = [(i if i % 20 else i - i % 40, draw.choice([1, 1, 2, 3, i]), 0, None if i % 9 == 0 else d) for i, d in enumerate(days)]
    rows += [(900 + i, 5000 + i // 2, 1, None) for i in range(6)] + [(950, 5000, 1, datetime(2024, 3, 1))]
    df = spark.createDataFrame(rows, "scene_id long, x long, y long, acquired_on timestamp_ntz")
    got = {r["scene_id"]: (r["tile"], r["gap"]) for r in pairing.closest_other(df, ["x", "y"], "scene_id", "acquired_on", "tile").collect()}
    db = duckdb.connect()
    db.sql("create table t (scene_id bigint, x bigint, y bigint, acquired_on timestamp)")
    db.executemany("insert into t values (?, ?, ?, ?)", rows)
    gap = "abs(date_diff('day', CAST(p.acquired_on AS DATE), CAST(c.acquired_on AS DATE)))"
    want = db.sql(f"select scene_id, tile, gap from (select p.scene_id, c.scene_id as tile, {gap} as gap, row_number() over (partition by p.scene_id order by {gap}, c.acquired_on, c.scene_id) as r from t p join t c using (x, y) where p.scene_id <> c.scene_id) where r = 1").fetchall()
    assert got == {s: (t, g) for s, t, g in want}


def test_closest_makes_no_pairs(spark, sf, tmp_path):
    """All orders at one place: no step makes more rows than there are orders."""
    t = lambda n: spark.read.parquet(f"{sf}/{n}.parquet")
    for n in ("customer", "nation", "region"):
        t(n).write.parquet(f"{tmp_path}/{n}.parquet")
    orders = t("orders").withColumn("o_custkey", F.lit(1).cast("long"))
    orders.write.parquet(f"{tmp_path}/orders.parquet")
    df = registry.queries()["m5_closest"](spark, str(tmp_path))
    n = orders.count()
    assert len(df.collect()) == n
    most, rest = 0, [df._jdf.queryExecution().executedPlan()]
    while rest:
        node = rest.pop()
        if node.metrics().contains("numOutputRows"):
            most = max(most, node.metrics().get("numOutputRows").get().value())
        rest += _children(node)
    assert most <= n


def _reads(spark, sf, name, tables):
    """The twin's rows, from files of these tables."""
    df = registry.queries()[name](spark, sf)
    assert {f.rsplit("/", 1)[1] for f in df.inputFiles()} == {f"{t}.parquet" for t in tables}
    _against_twin(spark, sf, name)


@pytest.mark.parametrize("name", ["m2_provenance", "m3_grid"])
def test_scenes_come_from_events(spark, sf, name):
    _reads(spark, sf, name, ["events"])


def test_mosaic_comes_from_tiles(spark, sf):
    _reads(spark, sf, "m5_mosaic", ["embeddings"])
    assert _most_broadcast(registry.queries()["m5_mosaic"](spark, sf)) <= spark.read.parquet(f"{sf}/embeddings.parquet").count()


def test_prompts_go_with_documents(spark, sf):
    _reads(spark, sf, "m7_prompts", ["documents"])


def test_refit_makes_no_corner_rows(spark, sf):
    """Pixels and their four corners stay in the patch's row: no step makes more rows than the three bands have cells."""
    df = registry.queries()["a6_refit"](spark, sf)
    tiles = spark.read.parquet(f"{sf}/embeddings.parquet").count()
    assert df.collect() == [(64 * tiles, 0)]
    most, rest = 0, [df._jdf.queryExecution().executedPlan()]
    while rest:
        node = rest.pop()
        if node.metrics().contains("numOutputRows"):
            most = max(most, node.metrics().get("numOutputRows").get().value())
        rest += _children(node)
    assert most <= 3 * 64 * tiles


@pytest.mark.parametrize("transform", ["stored", "refit"])
def test_reconstruction_in_rows(spark, transform):
    """The pixels of the long form: whole tiles, some with cells that are absent, null, doubled or outside, a tile without cells, a map that is none, two samples of a tile."""
    import random

    from radarlake.methods import align, release

    draw = random.Random(3)
    cells = [(t, v, u, draw.uniform(0, 255)) for t in range(6) for v in range(4) for u in range(5) if t < 3 or draw.random() < 0.6]
    cells += [(4, 1, 2, 7.0), (4, 1, 2, 9.0), (5, 0, 0, None), (5, 4, 0, 50.0), (5, 0, 5, 60.0), (5, -1, 2, 70.0)]
    maps = [(k, k % 7, (0.5 + k % 3 * 0.1, k % 4 * 0.1, k % 5 * 0.3, -(k % 3) * 0.1, 0.4 + k % 2 * 0.1, k % 6 * 0.2)) for k in range(14)]
    maps += [(14, 1, None), (15, 2, (1.0, 0.0, 0.0, 0.0, 1.0, 0.0)), (16, 0, (1e300, 0.0, 0.0, 0.0, 1.0, 0.0))]
    samples = spark.createDataFrame(maps, "key long, tile_id long, map struct<" + ", ".join(f"{f}: double" for f in align.FIELDS) + ">")
    table = spark.createDataFrame(cells, "tile_id long, v int, u int, value double")

    class Source:
        def tiles(self, wanted):
            return table

    at = lambda x, y: (F.lit(x), F.lit(y), *align.apply(F.col("map"), F.lit(x), F.lit(y)))
    points = [at(x, y) for x, y in ((0.0, 0.0), (5.0, 0.0), (0.0, 5.0))]
    long = release.reconstruct(samples, Source(), "key", 6, 5, 4, transform, points)
    rows = release.reconstruct_rows(samples, Source(), "key", 6, 5, 4, transform, points)
    got = {tuple(r[:4]): r[4] for r in rows.select("key", F.inline("pixels")).collect()}
    want = {tuple(r[:4]): r[4] for r in long.select("key", "x", "y", "inside", "value").collect()}
    assert len(got) == 36 * len(maps) and got == pytest.approx(want, abs=1e-9)
    assert sum(v > 0 for v in got.values()) > 100


def test_refit_counts_what_differs(spark, sf, monkeypatch):
    """Maps fitted a quarter of a pixel off: as many pixels apart as the long form has."""
    from radarlake.methods import align, release
    from radarlake.queries import studies

    fit = align.fit
    monkeypatch.setattr(align, "fit", lambda points: fit([(x, y, u + 0.25, v) for x, y, u, v in points]))
    long = [{r[:3]: r[3:] for r in map(tuple, studies._reconstructed(spark, sf, t, release.reconstruct).select("key", "x", "y", "inside", "value").collect())} for t in ("stored", "refit")]
    want = sum(i and long[1][k][0] and abs(x - long[1][k][1]) > 1e-4 for k, (i, x) in long[0].items())
    assert registry.queries()["a6_refit"](spark, sf).collect() == [(len(long[0]), want)] and want > 1000
