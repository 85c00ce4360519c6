"""Measures, generator, readers and approximate queries against brute force and invariants."""

import itertools
import math
import os
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from radarlake import registry
from radarlake.io import encode, tarshard
from radarlake.methods import caption, evaluate, generate, release, select


def naive_lcs(a, b):
    best = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    for i, j in itertools.product(range(len(a)), range(len(b))):
        best[i + 1][j + 1] = best[i][j] + 1 if a[i] == b[j] else max(best[i][j + 1], best[i + 1][j])
    return best[-1][-1]


def test_lcs_against_brute_force():
    rng = np.random.default_rng(0)
    for _ in range(300):
        a, b = (rng.choice(list("abcd"), rng.integers(0, 90)).tolist() for _ in range(2))
        assert evaluate.lcs(a, b) == naive_lcs(a, b)


def test_rouge_query_against_brute_force(spark, sf):
    c = {(r["conv_id"], r["turn"]): r for r in spark.read.parquet(f"{sf}/conversations.parquet").collect()}
    rows = registry.queries()["e_rouge"](spark, sf).collect()
    assert len(rows) == sum(r["role"] == "user" and c.get((k[0], k[1] + 1), {"role": ""})["role"] == "assistant" for k, r in c.items())
    for r in rows[:60]:
        a, b = c[r["conv_id"], r["turn"]]["text"].lower().split(), c[r["conv_id"], r["turn"] + 1]["text"].lower().split()
        n = naive_lcs(a, b)
        p, q = n / len(b), n / len(a)
        assert math.isclose(r["rouge_l"], (1 + 1.44) * p * q / (q + 1.44 * p) if n else 0.0, abs_tol=1e-12)


def test_text_measures_by_hand(spark):
    same = "a radar image of a port".split()
    assert evaluate.meteor_exact(same, same) == pytest.approx(1 - 0.5 * (1 / 6) ** 3)
    # three of four words in two pieces
    assert evaluate.meteor_exact(["a", "b", "c", "d"], ["c", "a", "b", "x"]) == pytest.approx(0.75 * (1 - 0.5 * (2 / 3) ** 3))
    assert evaluate.meteor_exact(["a"], ["b"]) == 0 and evaluate.meteor_exact([], []) == 0
    assert evaluate.greedy_cosine(same, same) == pytest.approx(1.0) and evaluate.greedy_cosine([], same) == 0.0
    one, two = ["x", "y"], ["y", "z", "w"]
    cos = evaluate.hashed_vectors(two) @ evaluate.hashed_vectors(one).T
    p = sum(max(cos[i]) for i in range(3)) / 3
    r = sum(max(cos[:, j]) for j in range(2)) / 2
    assert evaluate.greedy_cosine(one, two) == pytest.approx(2 * p * r / (p + r))
    df = spark.createDataFrame([(1, "a b c", "a b d"), (2, None, "x"), (3, "", ""), (4, "Q r", "q R")], "k int, reference string, candidate string")
    got = {x["k"]: x for x in evaluate.captioning(df).collect()}
    assert got[1]["f1"] == pytest.approx(2 / 3) and got[4]["rouge_l"] == 1.0 and got[2]["meteor"] == 0.0 and got[3]["cosine"] == 0.0
    assert evaluate.captioning(df.limit(0)).count() == 0


@pytest.mark.parametrize("n", [0, 1, 2, 3, 50, 700])
def test_shifted_pairs_are_a_derangement(spark, n):
    df = spark.createDataFrame([(i, f"c{i}") for i in range(n)], "k long, candidate string")
    got = [(r["k"], r["candidate"]) for r in evaluate.shifted(df, ["k"]).collect()]
    assert sorted(k for k, _ in got) == list(range(n)) and sorted(c for _, c in got) == sorted(f"c{i}" for i in range(n))
    assert n < 2 or all(c != f"c{k}" for k, c in got)


def test_control_auc_by_hand(spark):
    a = spark.createDataFrame([(0.9,), (0.5,), (0.5,)], "s double")
    b = spark.createDataFrame([(0.5,), (0.1,)], "s double")
    r = evaluate.control(a, b, "s").first()
    assert r["auc"] == pytest.approx((2 + 1.5 + 1.5) / 6) and r["gap"] == pytest.approx(1.9 / 3 - 0.3)


def test_hyperplane_recall(spark, sf):
    assert registry.queries()["e_lsh_recall"](spark, sf).first()["recall"] >= 0.9
    e = spark.read.parquet(f"{sf}/embeddings.parquet")
    assert evaluate.retrieval_lsh(e.limit(0), e, 3).count() == 0


def patches(spark, n=240, width=16, classes=3):
    rng = np.random.default_rng(5)
    mean = rng.normal(size=(classes, width)) * 2
    return spark.createDataFrame([(i, i % classes, (mean[i % classes] + rng.normal(size=width) * 0.3).tolist()) for i in range(n)], "key long, label int, x array<double>"), mean


def test_denoiser_is_the_ridge_solution(spark):
    df, _ = patches(spark)
    model = generate.fit_denoiser(df.repartition(3), 16, 3, schedule=(1.0, 0.5))
    rows = df.orderBy("key").collect()
    x = np.array([r["x"] for r in rows])
    d = generate._design(np.sqrt(0.5) * x + np.sqrt(0.5) * generate._normal([r["key"] for r in rows], 1, 0, 16), np.array([r["label"] for r in rows]), 3)
    assert np.allclose(model.matrices[0], np.linalg.solve(d.T @ d + 1e-2 * np.eye(20), d.T @ x))


def test_generated_patches_follow_their_class(spark):
    df, mean = patches(spark)
    model = generate.fit_denoiser(df, 16, 3)
    wanted = spark.createDataFrame([(i, i % 3) for i in range(90)], "key long, label int")
    made = {r["key"]: np.array(r["x"]) for r in generate.text_to_image(model, wanted).collect()}
    for k, x in made.items():
        assert np.argmin(((mean - x) ** 2).sum(1)) == k % 3
    again = {r["key"]: r["x"] for r in generate.text_to_image(model, wanted.repartition(4)).collect()}
    assert all(np.allclose(again[k], made[k]) for k in made)


def test_variants_and_painting(spark):
    df, mean = patches(spark)
    model = generate.fit_denoiser(df, 16, 3)
    real = {r["key"]: np.array(r["x"]) for r in df.collect()}
    same = {r["key"]: np.array(r["x"]) for r in generate.variant(model, df, 0.0).collect()}
    assert all(np.array_equal(same[k], real[k]) for k in real)
    moved = df.withColumn("label", (F.col("label") + 1) % 3)
    far = [np.mean([np.linalg.norm(np.array(r["x"]) - real[r["key"]]) for r in generate.variant(model, moved, s).collect()]) for s in (0.2, 0.6, 1.0)]
    assert far == sorted(far)
    for given in (np.arange(16) < 8, np.arange(16) >= 4, np.zeros(16, bool)):
        made = {r["key"]: np.array(r["x"]) for r in generate.inpaint(model, df, given).collect()}
        assert all(np.allclose(made[k][given], real[k][given]) for k in real)
    assert generate.inpaint(model, df.limit(0), given).count() == 0


def test_adapter_error_falls_with_rank(spark):
    df, _ = patches(spark)
    base = generate.fit_denoiser(df.filter("key < 30"), 16, 3)
    errors = [sum(generate.fit_adapter(base, df.filter("key >= 30"), r)[1]) for r in (0, 1, 2, 4, 8, 16)]
    assert all(b <= a + 1e-9 for a, b in zip(errors, errors[1:])) and errors[-1] < errors[0]
    model, _ = generate.fit_adapter(base, df, 2)
    assert model.parameters() == (5 * 20 * 16, 5 * (20 * 2 + 2 * 16)) and all(a is b for a, b in zip(model.matrices, base.matrices))


def test_quality_tells_makers_apart(spark):
    df, _ = patches(spark)
    model = generate.fit_denoiser(df, 16, 3)
    mean = lambda d: generate.quality(d, df).agg(F.avg("mean_distance")).first()[0]
    wanted = df.select("key", "label")
    assert mean(generate.variant(model, df, 0.0)) == 0 and mean(generate.text_to_image(model, wanted)) < 0.5
    near = generate.nearest_real(wanted, df).collect()
    assert len(near) == 240 and len({tuple(r["x"]) for r in near}) == 3


def test_png_round_trip(spark):
    rng = np.random.default_rng(0)
    for shape in ((1, 1), (3, 7), (64, 5)):
        image = rng.integers(0, 256, shape).astype(np.uint8)
        assert np.array_equal(encode.unpng(encode.png(image)), image)
    raw = bytearray(encode.png(image))
    raw[45] ^= 1
    with pytest.raises(ValueError):
        encode.unpng(bytes(raw))
    df = spark.createDataFrame([(1, [0, 255, 7, 8, 9, 10]), (2, None)], "k int, p array<int>")
    got = {r["k"]: r["i"] for r in df.select("k", encode.from_png(encode.to_png(F.col("p"), F.lit(3))).alias("i")).collect()}
    assert got[1]["pixels"] == [0, 255, 7, 8, 9, 10] and (got[1]["cols"], got[1]["rows"]) == (3, 2) and got[2] is None


def test_shards_are_read_shuffled(spark, tmp_path):
    spark.dataSource.register(tarshard.TarShards)
    rows = [(f"k{i:03d}", {"txt": f"v{i}".encode()}) for i in range(200)]
    spark.createDataFrame(rows, tarshard.SCHEMA).repartition(6, "key").sortWithinPartitions("key").write.format("tarshard").mode("append").save(str(tmp_path))
    assert len(os.listdir(tmp_path)) > 1
    read = lambda seed, n: [(r["key"], bytes(r["members"]["txt"])) for r in tarshard.read_shuffled(spark, str(tmp_path), seed, n).collect()]
    one = read(1, 40)
    assert sorted(one) == [(k, m["txt"]) for k, m in rows] and one == read(1, 40)
    assert one != read(2, 40) and one != sorted(one)


def test_contamination_of_odd_texts(spark):
    train = spark.createDataFrame([(1, None), (2, ""), (3, "a b c"), (4, "x " + "w1 w2 w3 w4 w5 w6 w7 w8 w9" + " y"), (5, "W1  w2\tw3 w4 w5 w6 w7 w8"), (6, "v " * 20000)], "doc_id long, text string")
    test = spark.createDataFrame([(1, "w1 w2 w3 w4 w5 w6 w7 w8 w9"), (2, None), (3, "a b c")], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r["shared"] for r in release.contamination(train, test).collect()}
    assert got == {(4, 1): 2, (5, 1): 1}
    assert release.contamination(train, test.limit(0)).count() == 0


def test_stacks_by_hand(spark):
    rows = [(1, 10, "2020-01-01"), (1, 11, "2020-01-20"), (1, 12, "2021-06-01"), (2, 13, "2020-01-01")]
    df = spark.createDataFrame(rows, "place int, key int, day string").withColumn("day", F.to_date("day"))
    got = {r["key"]: (r["stack"], r["layer"], r["gap"]) for r in select.temporal(df, "place", "day", "key", 30).collect()}
    assert got == {10: (1, 1, None), 11: (1, 2, 19), 12: (2, 1, 498), 13: (1, 1, None)}


def test_cover_against_brute_force(spark, sf):
    """Tiles of each footprint by the corners of the box, and each tile asked for once."""
    rows = registry.queries()["m5_cover"](spark, sf).collect()
    got = {}
    for r in rows:
        got.setdefault(r["scene_id"], set()).add((r["x"], r["y"]))
    tile_x = lambda lon: math.floor((lon + 180) / 360 * 4096) % 4096
    tile_y = lambda lat: min(max(math.floor((1 - math.asinh(math.tan(math.radians(max(min(lat, 85.05112878), -85.05112878)))) / math.pi) / 2 * 4096), 0), 4095)
    for r in spark.read.parquet(f"{sf}/orders.parquet").select("o_orderkey", "o_custkey").collect():
        lat, lon = r[1] * 13 % 161 - 80, r[1] * 29 % 360 - 180
        west = lon - 0.02 + (360 if lon - 0.02 < -180 else 0)
        xs, x = {tile_x(west)}, tile_x(west)
        while x != tile_x(lon + 0.03):
            x = (x + 1) % 4096
            xs.add(x)
        assert got[r[0]] == set(itertools.product(xs, range(tile_y(lat + 0.06), tile_y(lat + 0.01) + 1)))
    asked = {(r["x"], r["y"]): r["patches"] for r in registry.queries()["m5_requests"](spark, sf).collect()}
    assert asked == Counter((r["x"], r["y"]) for r in rows)


def test_approximate_queries_keep_their_bounds(spark, sf):
    q = registry.queries()
    exact = {r["variant"]: r["vocabulary"] for r in q["m7_vocab"](spark, sf).collect()}
    for r in q["m7_vocab_approx"](spark, sf).collect():
        assert abs(r["vocabulary"] / exact[r["variant"]] - 1) < 0.06
    exact = {r["variant"]: r for r in q["m7_pct"](spark, sf).collect()}
    for r in q["m7_pct_approx"](spark, sf).collect():
        assert abs(r["p10"] - exact[r["variant"]]["p10"]) <= 1 and abs(r["p90"] - exact[r["variant"]]["p90"]) <= 1


def test_approximate_aggregates_keep_their_bounds(spark, sf):
    r = registry.queries()["op_agg_approx"](spark, sf).first()
    t = spark.read.parquet(f"{sf}/lineitem.parquet")
    assert abs(r["orders"] / t.select("l_orderkey").distinct().count() - 1) < 0.06
    below = t.agg(F.avg((F.col("l_quantity") <= r["median"]).cast("int")), F.avg((F.col("l_quantity") < r["median"]).cast("int"))).first()
    assert below[0] >= 0.5 - 1e-3 and below[1] <= 0.5 + 1e-3


def test_round_trip_is_exact(spark, sf):
    assert all(r["exact"] for r in registry.queries()["a2_round_trip"](spark, sf).collect())


def test_build_holds_together(spark, sf):
    """The release table: unique keys, one split a scene, cleaned captions, fitted maps."""
    rows = registry.queries()["w1_build"](spark, sf).collect()
    assert len({r["key"] for r in rows}) == len(rows) > 0
    splits = {}
    for r in rows:
        splits.setdefault(r["scene_id"], set()).add(r["split"])
        assert r["map"] is not None and r["rms"] < 0.5 and 0 <= r["inside"] <= 1 and r["valid"] >= 0.5
        assert r["mid"] is None or r["mid"] == "" or (r["mid"][0] == r["mid"][0].upper() and r["mid"].endswith("."))
    # the fifth scene is not resampled, and at this size too few of its cells are present
    assert all(len(s) == 1 for s in splits.values()) and {"click", "error", "signup", "purchase"} <= set(splits)


def test_model_cleaner_keeps_nulls(spark):
    df = spark.createDataFrame([(1, "a red port  , near the sea"), (2, None)], "k int, text string")
    got = {r["k"]: r["text"] for r in caption.clean_with(df, lambda texts: [t.upper() for t in texts]).collect()}
    assert got[2] is None and got[1].startswith("A PORT, NEAR THE SEA")


def test_assembled_samples_go_through_shards(spark, sf, tmp_path):
    from radarlake.queries.studies import assembled

    spark.dataSource.register(tarshard.TarShards)
    want = {r["key"]: r["members"] for r in assembled(spark, sf).collect()}
    assembled(spark, sf).coalesce(2).write.format("tarshard").mode("append").save(str(tmp_path))
    got = {r["key"]: r["members"] for r in spark.read.format("tarshard").load(str(tmp_path)).collect()}
    assert got == want and len(got) == 500
    e = {r["vec_id"]: r["embedding"] for r in spark.read.parquet(f"{sf}/embeddings.parquet").collect()}
    from hashlib import md5

    for i in sorted(e)[::100]:
        x = np.frombuffer(bytes(got[md5(str(i).encode()).hexdigest()]["complex.bin"]), "<c8")
        assert np.allclose(x.real, e[i]) and np.allclose(x.imag, np.roll(e[i], -32))
        assert encode.unpng(bytes(got[md5(str(i).encode()).hexdigest()]["preview.png"])).shape == (8, 8)
