"""Keys, splits, shards and audits of a released corpus."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

BUCKETS = 10_000
SPLITS = ("train", "validation", "test")
#: Components and whether their licence lets them be passed on, with the credit they need.
LICENCES = (("radar", True, "CC-BY-4.0"), ("metadata", True, "CC-BY-4.0"), ("captions", True, "CC-BY-4.0"), ("optical", False, None))


def key(*columns: str) -> Column:
    """A sample's key; it holds no dot, so that member names split at the first one."""
    return F.md5(F.concat_ws("-", *columns))


def bucket(by: Column, buckets: int = BUCKETS) -> Column:
    """A stable number below `buckets` of a value, from the first eight digits of its MD5."""
    return F.conv(F.substring(F.md5(by.cast("string")), 1, 8), 16, 10).cast("long") % buckets


def split_name(share: Column, ratios: tuple[float, ...] = (0.8, 0.1, 0.1)) -> Column:
    return F.when(share < ratios[0], SPLITS[0]).when(share < ratios[0] + ratios[1], SPLITS[1]).otherwise(SPLITS[2])


def split(df: DataFrame, by: str, ratios: tuple[float, ...] = (0.8, 0.1, 0.1)) -> DataFrame:
    """A split as a function of the pass alone: no shuffle, and it stays when data are added."""
    return df.withColumn("split", split_name(bucket(F.col(by)) / BUCKETS, ratios))


def _running(df: DataFrame, weight: str, order: list[str], part: str) -> DataFrame:
    """Running sums before each row in the order, in two levels: within ranges of `part`, plus the totals of the ranges before."""
    inside = Window.partitionBy(part).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    local = df.withColumn("_in", F.coalesce(F.sum(weight).over(inside), F.lit(0)))
    totals = df.groupBy(part).agg(F.sum(weight).alias("_t"))
    # one row a range
    before = Window.partitionBy(F.lit(1)).orderBy(part).rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select(part, F.coalesce(F.sum("_t").over(before), F.lit(0)).alias("_off"))
    return local.join(F.broadcast(offsets), part).withColumn("before", F.col("_in") + F.col("_off")).drop("_in", "_off")


def split_balanced(df: DataFrame, by: str, ratios: tuple[float, ...] = (0.8, 0.1, 0.1), parts: int = 256) -> DataFrame:
    """Passes in the order of their hash, split where the running share of samples crosses the ratios: at most a pass off."""
    h = F.md5(F.col(by).cast("string"))
    passes = df.groupBy(by).agg(F.count("*").alias("n")).withColumn("h", h).withColumn("part", F.conv(F.substring("h", 1, 2), 16, 10).cast("int"))
    ran = _running(passes, "n", ["h", by], "part")
    total = passes.agg(F.sum("n").alias("total"))
    named = ran.crossJoin(F.broadcast(total)).withColumn("split", split_name(F.col("before") / F.col("total"), ratios))
    return named.select(by, "n", "split")


def split_stratified(df: DataFrame, by: str, stratum: str, ratios: tuple[float, ...] = (0.8, 0.1, 0.1)) -> DataFrame:
    """Passes of each stratum in the order of their hash, split at the ratios of their number.

    Ranks are taken inside ranges of the hash and moved by the stratum's ranges before, so that a large stratum lies in no single task.
    """
    h = F.md5(F.col(by).cast("string"))
    passes = df.select(by, stratum).distinct().withColumn("_h", h).withColumn("_part", F.substring("_h", 1, 2))
    local = passes.withColumn("_in", F.row_number().over(Window.partitionBy(stratum, "_part").orderBy("_h", by)) - 1)
    # at most 256 rows a stratum
    before = Window.partitionBy("_s").orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    totals = passes.groupBy(F.col(stratum).alias("_s"), F.col("_part").alias("_p")).agg(F.count("*").alias("_n"))
    offsets = totals.select("_s", "_p", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_off"), F.sum("_n").over(Window.partitionBy("_s")).alias("_all"))
    joined = local.join(offsets, local[stratum].eqNullSafe(offsets["_s"]) & (local["_part"] == offsets["_p"]))
    return joined.withColumn("split", split_name((F.col("_in") + F.col("_off")) / F.col("_all"), ratios)).select(by, stratum, "split")


def split_random(df: DataFrame, *unique: str, ratios: tuple[float, ...] = (0.8, 0.1, 0.1)) -> DataFrame:
    """Baseline: each sample on its own, so that passes fall into several splits."""
    return df.withColumn("split", split_name(bucket(F.concat_ws("-", *unique)) / BUCKETS, ratios))


def leakage(df: DataFrame, by: str) -> DataFrame:
    """How many values of `by` there are, and how many lie in more than one split."""
    n = df.groupBy(by).agg(F.count_distinct("split").alias("splits"))
    return n.agg(F.count("*").alias("values"), F.count_if(F.col("splits") > 1).alias("leaking"))


def shards(df: DataFrame, max_bytes: int, per_chunk: int = 16, size: str = "bytes", key_: str = "key") -> DataFrame:
    """Chunk, shard and path of each sample: keys in their order, cut where the running bytes of a split cross `max_bytes`."""
    part = df.withColumn("_part", F.concat("split", F.substring(key_, 1, 2)))
    inside = Window.partitionBy("_part").orderBy(key_).rowsBetween(Window.unboundedPreceding, -1)
    local = part.withColumn("_in", F.coalesce(F.sum(size).over(inside), F.lit(0)))
    totals = part.groupBy("split", "_part").agg(F.sum(size).alias("_t"))
    before = Window.partitionBy("split").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select("_part", F.coalesce(F.sum("_t").over(before), F.lit(0)).alias("_off"))
    placed = local.join(F.broadcast(offsets), "_part").withColumn("shard", F.floor((F.col("_in") + F.col("_off")) / max_bytes).cast("long"))
    chunk = F.floor(F.col("shard") / per_chunk).cast("long")
    path = F.format_string("%s/chunk_%d/shard-%d.tar", F.col("split"), chunk, F.col("shard"))
    return placed.withColumn("chunk", chunk).withColumn("path", path).drop("_in", "_off", "_part")


def shuffled(df: DataFrame, seed: int, key_: str = "key") -> DataFrame:
    """The place, from 1, of each sample in its split in the order of a seeded hash: ranks in ranges of the hash, moved by the ranges before."""
    ranged = df.withColumn("_h", F.md5(F.concat(F.lit(str(seed)), key_))).withColumn("_part", F.concat("split", F.substring("_h", 1, 3)))
    local = ranged.withColumn("_in", F.row_number().over(Window.partitionBy("_part").orderBy("_h", key_)))
    totals = ranged.groupBy("split", "_part").agg(F.count("*").alias("_t"))
    # at most 4096 rows a split
    before = Window.partitionBy("split").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select("_part", F.coalesce(F.sum("_t").over(before), F.lit(0)).alias("_off"))
    return local.join(F.broadcast(offsets), "_part").withColumn("place", F.col("_in") + F.col("_off")).drop("_h", "_part", "_in", "_off")


def license_filter(df: DataFrame, component: str = "component") -> DataFrame:
    """Rows of components that may be passed on, with their credit."""
    policy = df.sparkSession.createDataFrame(LICENCES, "component string, redistributable boolean, attribution string").filter("redistributable")
    return df.join(F.broadcast(policy.select(F.col("component").alias(component), "attribution")), component)


def volume(df: DataFrame, component: str = "component", size: str = "bytes") -> DataFrame:
    return df.groupBy(component).agg(F.count("*").alias("members"), F.sum(size).alias("bytes"))


#: Bytes of test texts whose runs are sent to all workers; a larger test set meets the texts in an exchange.
SENT_BYTES = 16 << 20


def contamination(train: DataFrame, test: DataFrame, n: int = 8, key_: str = "doc_id", item: str = "item_id") -> DataFrame:
    """Pairs of texts and test items that share a run of n words, and how many distinct ones.

    A run goes by a 64-bit hash that is chained over its words. Null and shorter texts have no run.
    """
    from radarlake.methods.caption import tokens
    from radarlake.methods.geo import bound

    def runs(df: DataFrame, k: str) -> DataFrame:
        def chained(s: Column) -> Column:
            # whole arrays, moved by a word and hashed pairwise: work grows with the words, not with places times words
            m = F.size(s["h"]) - n + 1
            made = F.slice(s["h"], 1, m)
            for j in range(1, n):
                made = F.zip_with(made, F.slice(s["h"], F.lit(j + 1), m), lambda a, b: F.xxhash64(a, b))
            return F.when(m > 0, F.array_distinct(made))

        # the words are split and hashed once
        hashed = bound({"h": F.transform(tokens(F.lower("text")), lambda w: F.xxhash64(w))}, chained)
        return df.select(k, F.explode(hashed).alias("h"))

    size = test.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("n")).first()["n"]
    asked = runs(test, item)
    met = runs(train, key_).join(F.broadcast(asked) if size <= SENT_BYTES else asked, "h")
    return met.groupBy(key_, item).agg(F.count("*").alias("shared"))


def reconstruct(samples: DataFrame, source, key_: str, size: int, width: int, height: int, transform: str = "stored", points=None) -> DataFrame:
    """Optical pixels of samples on the radar grid, made on read: tiles from the source, the map stored or fitted anew from corners, a warp.

    `samples` has the key, `tile_id` and, for `stored`, `map`; `points` are corner correspondences of a row, for `refit`.
    """
    from radarlake.methods import align

    wanted = _wanted(samples, key_, transform, points)
    return align.warp_join(align.map_pixels(wanted, size), source.tiles(wanted), [key_], width, height)


def reconstruct_rows(samples: DataFrame, source, key_: str, size: int, width: int, height: int, transform: str = "stored", points=None) -> DataFrame:
    """The same with a row a sample, its pixels in an array `pixels` (x, y, inside, value): a map meets its tile's image, and no pixel is exchanged."""
    from radarlake.methods import align

    wanted = _wanted(samples, key_, transform, points)
    met = wanted.join(align.images(source.tiles(wanted), width, height), "tile_id", "left")
    return align.warp_rows(met, size, width, height).select(key_, "tile_id", "pixels")


def _wanted(samples: DataFrame, key_: str, transform: str, points) -> DataFrame:
    """Samples with the map to use."""
    from radarlake.methods import align

    if transform not in ("stored", "refit"):
        raise ValueError(f"{transform}: the transform is stored or refit")
    mapped = samples if transform == "stored" else samples.withColumn("map", align.fit(points))
    return mapped.select(key_, "tile_id", "map")


def assemble(samples: DataFrame, meta: list[str], payload: str = "payload", pixels: str = "pixels", cols: str = "cols") -> DataFrame:
    """Sample records (key, members) as shards hold them: the complex array's bytes, a grey preview as PNG, and the columns `meta` as XML and as JSON.

    A sample without a part has no member of that name.
    """
    from radarlake.io.encode import to_png

    about = F.struct(*meta)
    members = {"complex.bin": F.col(payload), "preview.png": to_png(F.col(pixels), F.col(cols)), "meta.xml": F.to_xml(about, {"rowTag": "sample"}).cast("binary"), "meta.json": F.to_json(about).cast("binary")}
    parts = F.array(*(F.struct(F.lit(k).alias("name"), v.alias("data")) for k, v in members.items()))
    return samples.select("key", F.map_from_entries(F.filter(parts, lambda m: m["data"].isNotNull())).alias("members"))
