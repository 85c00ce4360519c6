"""More of the relational surface: sources, multisets, special joins, ranges, user functions."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from radarlake.io import shared
from radarlake.methods import pairing, release
from radarlake.registry import query
from radarlake.standins import acquisitions, scene_cells, table, vec_patches, with_views

_R = lambda c, n=6: (F.round(c, n) + 0.0)
C = F.col


# --- sources ----------------------------------------------------------------------


def formats(df: DataFrame, kinds: tuple[str, ...] = ("csv", "json", "orc")) -> DataFrame:
    """The rows after a round trip through each format, under the given schema."""
    spark, out = df.sparkSession, None
    for kind in kinds:
        where = shared.path(spark, kind)
        df.write.format(kind).save(where)
        back = spark.read.format(kind).schema(df.schema).load(where).withColumn("format", F.lit(kind))
        out = back if out is None else out.unionByName(back)
    return out


@query("SELECT p_partkey, p_name, p_size, p_retailprice, f AS format FROM part, (VALUES ('csv'), ('json'), ('orc')) t(f)")
def op_scan_formats(spark, sf):
    return formats(table(spark, sf, "part").select("p_partkey", "p_name", "p_size", "p_retailprice"))


@query()
def op_binary_scan(spark, sf):
    files = spark.read.format("binaryFile").load(f"{sf}/region.parquet")
    return files.select(F.element_at(F.split("path", "/"), -1).alias("name"), "length", F.length("content").cast("long").alias("read"), F.substring("content", 1, 4).cast("string").alias("magic"))


@query("SELECT event_id, user_id, event_type, value FROM events")
def op_json_roundtrip(spark, sf):
    row = table(spark, sf, "events").select(F.to_json(F.struct("event_id", "user_id", "event_type", "value")).alias("j"))
    return row.select(F.from_json("j", "event_id long, user_id long, event_type string, value double").alias("s")).select("s.*")


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k, json_type(props, '$.k') IS NOT NULL AS has_k FROM events")
def op_variant(spark, sf):
    v = table(spark, sf, "events").select("event_id", F.try_parse_json("props").alias("v"))
    return v.select("event_id", F.try_variant_get("v", "$.k", "int").alias("k"), F.try_variant_get("v", "$.k", "string").isNotNull().alias("has_k"))


@query("SELECT n_nationkey, n_name, n_regionkey FROM nation")
def op_xml(spark, sf):
    """A metadata member as XML, written and read by path and by schema."""
    x = table(spark, sf, "nation").select(F.to_xml(F.struct("n_nationkey", "n_name", "n_regionkey"), {"rowTag": "nation"}).alias("x"))
    read = F.from_xml("x", "n_nationkey int, n_regionkey int")
    return x.select(read["n_nationkey"].alias("n_nationkey"), F.xpath_string("x", F.lit("nation/n_name")).alias("n_name"), read["n_regionkey"].alias("n_regionkey"))


@query("SELECT 'documents' AS source, count(*) AS n_rows, count(*) FILTER (text IS NULL) AS n_null, CAST(coalesce(max(n_chars), 0) AS BIGINT) AS longest FROM documents")
def op_observe(spark, sf):
    """Counters taken while the rows pass by on their way to a sink."""
    seen = Observation("documents")
    counters = (F.count(F.lit(1)).alias("n_rows"), F.count_if(C("text").isNull()).alias("n_null"), F.coalesce(F.max("n_chars"), F.lit(0)).alias("longest"))
    table(spark, sf, "documents").select("text", "n_chars").observe(seen, *counters).write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([("documents", *(seen.get[k] for k in ("n_rows", "n_null", "longest")))], "source string, n_rows long, n_null long, longest long")


# --- sets and subqueries ----------------------------------------------------------


@query("SELECT 'customer' AS kind, c_custkey AS id, c_nationkey AS nation FROM customer UNION ALL SELECT 'supplier', s_suppkey, s_nationkey FROM supplier")
def op_union(spark, sf):
    c = table(spark, sf, "customer").select(F.lit("customer").alias("kind"), C("c_custkey").alias("id"), C("c_nationkey").alias("nation"))
    return c.union(table(spark, sf, "supplier").select(F.lit("supplier").alias("kind"), C("s_suppkey").alias("id"), C("s_nationkey").alias("nation")))


def _nations(spark, sf):
    return table(spark, sf, "customer").select(C("c_nationkey").alias("nation")), table(spark, sf, "supplier").select(C("s_nationkey").alias("nation"))


@query("SELECT nation, count(*) AS n FROM (SELECT c_nationkey AS nation FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier) GROUP BY 1")
def op_intersect_all(spark, sf):
    c, s = _nations(spark, sf)
    return c.intersectAll(s).groupBy("nation").agg(F.count("*").alias("n"))


@query("SELECT nation, count(*) AS n FROM (SELECT c_nationkey AS nation FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier) GROUP BY 1")
def op_except_all(spark, sf):
    c, s = _nations(spark, sf)
    return c.exceptAll(s).groupBy("nation").agg(F.count("*").alias("n"))


@query("SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal > 9000)")
def op_in_sub(spark, sf):
    text = "SELECT o_orderkey, o_totalprice FROM {o} WHERE o_custkey IN (SELECT c_custkey FROM {c} WHERE c_acctbal > 9000)"
    return spark.sql(text, o=table(spark, sf, "orders"), c=table(spark, sf, "customer"))


_CTE = """WITH spend AS (SELECT o_custkey, sum(o_totalprice) AS total, count(*) AS n FROM {orders} GROUP BY o_custkey),
mean AS (SELECT avg(total) AS m FROM spend),
high AS (SELECT o_custkey, total, n FROM spend, mean WHERE total > 2 * m)
SELECT c_nationkey AS nation, count(*) AS customers, sum(n) AS passes FROM high JOIN {customer} ON c_custkey = o_custkey GROUP BY c_nationkey"""


@query(_CTE.format(orders="orders", customer="customer").replace("sum(n)", "CAST(sum(n) AS BIGINT)"))
def op_cte(spark, sf):
    return spark.sql(_CTE, orders=table(spark, sf, "orders"), customer=table(spark, sf, "customer"))


_TILE12 = "CAST(floor((lon0 + 180e0) / 360e0 * 4096) AS BIGINT) % 4096 AS x, CAST(floor((1e0 - ln(tan(radians(lat0)) + 1e0 / cos(radians(lat0))) / pi()) / 2e0 * 4096) AS BIGINT) AS y"


@query(with_views("acq", f", t AS (SELECT 12 AS z, {_TILE12} FROM acq), up AS (SELECT z, x, y FROM (SELECT DISTINCT * FROM t) UNION SELECT z - 1, x // 2, y // 2 FROM up WHERE z > 0) SELECT CAST(z AS INT) AS z, x, y FROM up"))
def op_quadtree(spark, sf):
    """All ancestors of the tiles that hold a scene; a tile's ancestor follows from its numbers, so no recursion is needed."""
    t = acquisitions(spark, sf).select(pairing.tile_x(C("lon0"), 12).alias("x"), pairing.tile_y(C("lat0"), 12).alias("y")).distinct()
    up = t.select("x", "y", F.explode(F.sequence(F.lit(0), F.lit(12))).alias("z"))
    scale = F.pow(F.lit(2.0), 12 - C("z"))
    return up.select("z", F.floor(C("x") / scale).cast("long").alias("x"), F.floor(C("y") / scale).cast("long").alias("y")).distinct()


# --- joins ------------------------------------------------------------------------


@query("""WITH b AS (SELECT s_suppkey, s_suppkey * 17 % 161 - 80 AS lat, s_suppkey * 31 % 360 - 180 AS lon FROM supplier), p AS (SELECT c_custkey, c_custkey * 13 % 161 - 80 AS lat, c_custkey * 29 % 360 - 180 AS lon FROM customer)
SELECT s_suppkey, count(*) AS points FROM b JOIN p ON p.lat BETWEEN b.lat - 3 AND b.lat + 3 AND p.lon BETWEEN b.lon - 3 AND b.lon + 3 GROUP BY 1""")
def op_join_range(spark, sf, cell: int = 8):
    """Points in boxes: a box goes to the grid cells that it touches, points meet it by cell, the exact test follows."""
    b = table(spark, sf, "supplier").select("s_suppkey", (C("s_suppkey") * 17 % 161 - 80).alias("lat"), (C("s_suppkey") * 31 % 360 - 180).alias("lon"))
    p = table(spark, sf, "customer").select((C("c_custkey") * 13 % 161 - 80).alias("p_lat"), (C("c_custkey") * 29 % 360 - 180).alias("p_lon"))
    at = lambda c: F.floor(c / cell)
    boxes = b.withColumn("i", F.explode(F.sequence(at(C("lat") - 3), at(C("lat") + 3)))).withColumn("j", F.explode(F.sequence(at(C("lon") - 3), at(C("lon") + 3))))
    met = boxes.join(p.withColumn("i", at(C("p_lat"))).withColumn("j", at(C("p_lon"))), ["i", "j"])
    return met.filter((F.abs(C("lat") - C("p_lat")) <= 3) & (F.abs(C("lon") - C("p_lon")) <= 3)).groupBy("s_suppkey").agg(F.count("*").alias("points"))


@query("""WITH d AS (SELECT a.o_orderkey, CAST(b.o_orderdate AS DATE) AS nearest, abs(date_diff('day', CAST(a.o_orderdate AS DATE), CAST(b.o_orderdate AS DATE))) AS days FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND a.o_orderkey <> b.o_orderkey)
SELECT o_orderkey, CAST(min(days) AS INT) AS days, arg_min(nearest, days * 100000 + date_diff('day', DATE '1970-01-01', nearest)) AS nearest FROM d GROUP BY 1""")
def op_join_nearest(spark, sf):
    """Each pass's nearest other pass of its city by date, ties to the earlier: it is a neighbour in the order of dates."""
    o = table(spark, sf, "orders").select("o_orderkey", "o_custkey", C("o_orderdate").cast("date").alias("day"))
    w = Window.partitionBy("o_custkey").orderBy("day", "o_orderkey")
    near = F.array(F.lag("day").over(w), F.lead("day").over(w))
    best = F.array_min(F.transform(F.filter(near, lambda x: x.isNotNull()), lambda x: F.struct(F.abs(F.datediff(x, "day")).alias("days"), x.alias("nearest"))))
    return o.withColumn("near", best).filter("near is not null").select("o_orderkey", "near.days", "near.nearest")


@query("""WITH c AS (SELECT c_custkey, CASE WHEN c_custkey % 7 <> 0 THEN c_nationkey END AS k FROM customer), n AS (SELECT CASE WHEN n_nationkey > 2 THEN n_nationkey END AS k, n_name FROM nation)
SELECT c.k AS nation, n.n_name, count(c_custkey) AS customers FROM c FULL JOIN n ON c.k = n.k GROUP BY ALL""")
def op_join_null_keys(spark, sf):
    """Null keys meet nothing and stay in an outer join."""
    c = table(spark, sf, "customer").select("c_custkey", F.when(C("c_custkey") % 7 != 0, C("c_nationkey")).alias("nation"))
    n = table(spark, sf, "nation").select(F.when(C("n_nationkey") > 2, C("n_nationkey")).alias("k"), "n_name")
    return c.join(n, C("nation") == C("k"), "full").groupBy("nation", "n_name").agg(F.count("c_custkey").alias("customers"))


# --- aggregates, windows, order ---------------------------------------------------


@query("SELECT l_orderkey, bool_and(l_quantity > 10) AS all_large, bool_or(l_discount > 0.05) AS some_cheap FROM lineitem GROUP BY 1")
def op_agg_bool(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_orderkey").agg(F.bool_and(C("l_quantity") > 10).alias("all_large"), F.bool_or(C("l_discount") > F.lit(0.05)).alias("some_cheap"))


@query(with_views("acq", "SELECT continent, pol, CAST(grouping(continent, pol) AS BIGINT) AS level, count(*) AS n, CAST(sum(incidence_deg) AS BIGINT) AS degrees FROM acq GROUP BY CUBE (continent, pol)"))
def op_agg_cube(spark, sf):
    return acquisitions(spark, sf).cube("continent", "pol").agg(F.grouping_id().alias("level"), F.count("*").alias("n"), F.sum("incidence_deg").alias("degrees"))


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY CAST(epoch(ts) AS BIGINT) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW), 4) AS hour_sum FROM events")
def op_win_range(spark, sf):
    # to the nearest second, halves to the even one, as the twin's cast does
    second = F.rint(F.unix_micros(C("ts").cast("timestamp")) / 1_000_000).cast("long")
    w = Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)
    return table(spark, sf, "events").withColumn("s", second).select("event_id", _R(F.sum("value").over(w), 4).alias("hour_sum"))


@query("SELECT CAST(row_number() OVER (ORDER BY o_orderpriority, o_totalprice DESC, o_orderkey) AS BIGINT) AS place, o_orderkey, o_orderpriority FROM orders")
def op_sort_global(spark, sf):
    """The place of each row in a total order: rows are numbered inside ranges of the leading keys, and ranges before them add up."""
    o = table(spark, sf, "orders").select("o_orderkey", "o_orderpriority", "o_totalprice").withColumn("one", F.lit(1))
    fall = F.lpad(F.floor((10_000_000 - C("o_totalprice")) / 2000).cast("string"), 8, "0")
    ran = release._running(o.withColumn("range", F.concat("o_orderpriority", fall)), "one", ["o_orderpriority", F.desc("o_totalprice"), "o_orderkey"], "range")
    return ran.orderBy("o_orderpriority", F.desc("o_totalprice"), "o_orderkey").select((C("before") + 1).cast("long").alias("place"), "o_orderkey", "o_orderpriority")


@query("SELECT n_name, c_custkey, c_acctbal, CAST(r AS INT) AS r FROM (SELECT n_name, c_custkey, c_acctbal, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer JOIN nation ON c_nationkey = n_nationkey) WHERE r <= 3")
def op_topk_group(spark, sf):
    """The three largest of each group; a filter on the rank lets tasks drop the others before the exchange."""
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    best = table(spark, sf, "customer").withColumn("r", F.row_number().over(w)).filter("r <= 3")
    return best.join(table(spark, sf, "nation"), C("c_nationkey") == C("n_nationkey")).select("n_name", "c_custkey", "c_acctbal", "r")


@query("SELECT c_nationkey, c_custkey FROM (SELECT c_nationkey, c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY md5(CAST(c_custkey AS VARCHAR)), c_custkey) AS r FROM customer) WHERE r <= 5")
def op_sample_strat(spark, sf):
    """Five of each nation in the order of a hash: the sample is the feature, and stays as rows are added elsewhere."""
    w = Window.partitionBy("c_nationkey").orderBy(F.md5(C("c_custkey").cast("string")), "c_custkey")
    return table(spark, sf, "customer").withColumn("r", F.row_number().over(w)).filter("r <= 5").select("c_nationkey", "c_custkey")


# --- structs, vectors, user functions ---------------------------------------------


@query("SELECT n_name, r_name, upper(r_name) || '/' || n_name AS path, CAST(n_nationkey AS BIGINT) * 10 + n_regionkey AS code FROM nation JOIN region ON n_regionkey = r_regionkey")
def op_struct(spark, sf):
    n = table(spark, sf, "nation").join(F.broadcast(table(spark, sf, "region")), C("n_regionkey") == C("r_regionkey"))
    s = n.select(F.struct(F.struct(C("n_name").alias("name"), C("n_nationkey").alias("key")).alias("nation"), F.struct(C("r_name").alias("name"), C("r_regionkey").alias("key")).alias("region")).alias("place"))
    s = s.withColumn("place", C("place").withField("region.upper", F.upper("place.region.name")))
    return s.select(C("place.nation.name").alias("n_name"), C("place.region.name").alias("r_name"), F.concat_ws("/", "place.region.upper", "place.nation.name").alias("path"), (C("place.nation.key").cast("long") * 10 + C("place.region.key")).alias("code"))


@query("""WITH p AS (SELECT a.vec_id, a.embedding AS x, b.embedding AS y FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1),
s AS (SELECT vec_id, list_sum([CAST(x[i] AS DOUBLE) * CAST(y[i] AS DOUBLE) FOR i IN range(1, 65)]) AS xy, list_sum([CAST(v AS DOUBLE) * CAST(v AS DOUBLE) FOR v IN x]) AS xx, list_sum([CAST(v AS DOUBLE) * CAST(v AS DOUBLE) FOR v IN y]) AS yy FROM p)
SELECT vec_id, round(xy, 5) + 0.0 AS dot, round(sqrt(xx), 5) AS norm, round(xy / sqrt(xx * yy), 5) + 0.0 AS cosine FROM s""")
def op_vector_sim(spark, sf):
    e = table(spark, sf, "embeddings").select("vec_id", C("embedding").cast("array<double>").alias("x"))
    p = e.join(e.select((C("vec_id") - 1).alias("vec_id"), C("x").alias("y")), "vec_id")
    inner = lambda a, b: F.aggregate(F.zip_with(a, b, lambda u, v: u * v), F.lit(0.0), lambda s, v: s + v)
    s = p.select("vec_id", inner("x", "y").alias("xy"), inner("x", "x").alias("xx"), inner("y", "y").alias("yy"))
    return s.select("vec_id", _R("xy", 5).alias("dot"), _R(F.sqrt("xx"), 5).alias("norm"), _R(C("xy") / F.sqrt(C("xx") * C("yy")), 5).alias("cosine"))


_AMP = "SELECT patch_id, r, c, round(sqrt(re * re + im * im), 6) AS amplitude FROM patches"


@query(with_views("patches", _AMP))
def op_udf_amp(spark, sf):
    @F.arrow_udf("double")
    def amplitude(re: pa.Array, im: pa.Array) -> pa.Array:
        return pc.sqrt(pc.add(pc.multiply(re, re), pc.multiply(im, im)))

    return vec_patches(spark, sf).select("patch_id", "r", "c", _R(amplitude("re", "im")).alias("amplitude"))


@query(with_views("patches", _AMP))
def op_sql_function(spark, sf):
    """A function declared in SQL and inlined by the optimiser, called from SQL text."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION radar_amplitude(re DOUBLE, im DOUBLE) RETURNS DOUBLE RETURN sqrt(re * re + im * im)")
    return spark.sql("SELECT patch_id, r, c, round(radar_amplitude(re, im), 6) AS amplitude FROM {p}", p=vec_patches(spark, sf))


@query("SELECT conv_id, turn, regexp_replace(trim(lower(text)), '[^a-z0-9]+', ' ', 'g') AS plain FROM conversations")
def op_pandas_udf(spark, sf):
    @F.pandas_udf("string")
    def plain(text: pd.Series) -> pd.Series:
        return text.str.lower().str.strip(" ").str.replace("[^a-z0-9]+", " ", regex=True)

    return table(spark, sf, "conversations").select("conv_id", "turn", plain("text").alias("plain"))


@query(with_views("cells", ", i AS (SELECT scene_id, re * re + im * im AS i FROM cells) SELECT scene_id, round(avg(i) * avg(i) / var_samp(i), 6) AS enl FROM i GROUP BY 1"))
def op_udaf_enl(spark, sf):
    """The equivalent number of looks as a grouped-aggregate function, for comparison with the built-in form."""

    @F.pandas_udf("double")
    def looks(i: pd.Series) -> float:
        return float(i.mean() ** 2 / i.var()) if len(i) > 1 and i.var() else None

    i = scene_cells(spark, sf).select("scene_id", (C("re") * C("re") + C("im") * C("im")).alias("i"))
    return i.groupBy("scene_id").agg(_R(looks("i")).alias("enl"))


@query("SELECT s_suppkey, CAST(x AS BIGINT) AS x, CAST(y AS BIGINT) AS y FROM supplier, range(64) a(x), range(64) b(y) WHERE x BETWEEN s_suppkey % 60 AND s_suppkey % 60 + 2 AND y BETWEEN s_suppkey % 50 AND s_suppkey % 50 + 1")
def op_udtf_tiles(spark, sf):
    @F.udtf(returnType="x: bigint, y: bigint")
    class Cover:
        def eval(self, west: int, east: int, north: int, south: int):
            for x in range(west, east + 1):
                for y in range(north, south + 1):
                    yield x, y

    spark.udtf.register("radar_cover", Cover)
    s = table(spark, sf, "supplier").select("s_suppkey", (C("s_suppkey") % 60).alias("w"), (C("s_suppkey") % 50).alias("n"))
    return spark.sql("SELECT s_suppkey, x, y FROM {s} b, LATERAL radar_cover(b.w, b.w + 2, b.n, b.n + 1)", s=s)
