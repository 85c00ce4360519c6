"""Scalar functions of the operator catalogue on the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from radarlake.registry import query
from radarlake.standins import table

_R = lambda c, n=6: (F.round(c, n) + 0.0)
C = F.col


@query("SELECT p_partkey, upper(p_name) AS up, lpad(CAST(p_size AS VARCHAR), 4, '0') AS padded, replace(p_name, ' ', '_') AS joined, reverse(p_name) AS turned, substr(p_name, 2, 3) AS part, CAST(length(p_name) AS INT) AS n FROM part")
def op_str_basic(spark, sf):
    p = table(spark, sf, "part")
    return p.select("p_partkey", F.upper("p_name").alias("up"), F.lpad(C("p_size").cast("string"), 4, "0").alias("padded"), F.replace("p_name", F.lit(" "), F.lit("_")).alias("joined"), F.reverse("p_name").alias("turned"), F.substring("p_name", 2, 3).alias("part"), F.length("p_name").alias("n"))


@query("SELECT doc_id, CAST(len(regexp_extract_all(text, '[0-9]+')) AS INT) AS numbers, regexp_extract(text, '([A-Za-z]+)', 1) AS first FROM documents")
def op_str_regex(spark, sf):
    return table(spark, sf, "documents").select("doc_id", F.regexp_count("text", F.lit("[0-9]+")).alias("numbers"), F.regexp_extract("text", "([A-Za-z]+)", 1).alias("first"))


@query("SELECT doc_id, md5(text) AS m, sha256(text) AS s FROM documents")
def op_str_hash(spark, sf):
    return table(spark, sf, "documents").select("doc_id", F.md5("text").alias("m"), F.sha2("text", 256).alias("s"))


@query("SELECT a.n AS a, b.n AS b, CAST(levenshtein(a.n, b.n) AS INT) AS d FROM (SELECT DISTINCT p_name AS n FROM part) a JOIN (SELECT DISTINCT p_name AS n FROM part) b ON a.n < b.n")
def op_str_distance(spark, sf):
    n = table(spark, sf, "part").select(C("p_name").alias("n")).distinct()
    return n.alias("x").join(F.broadcast(n.alias("y")), C("x.n") < C("y.n")).select(C("x.n").alias("a"), C("y.n").alias("b"), F.levenshtein("x.n", "y.n").alias("d"))


@query("SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, CAST(quarter(o_orderdate) AS INT) AS q, CAST(weekofyear(o_orderdate) AS INT) AS w, CAST(dayofyear(o_orderdate) AS INT) AS d FROM orders")
def op_date_parts(spark, sf):
    return table(spark, sf, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"), F.weekofyear("o_orderdate").alias("w"), F.dayofyear("o_orderdate").alias("d"))


@query("SELECT o_orderkey, CAST(o_orderdate AS DATE) + 30 AS later, CAST(date_trunc('month', o_orderdate) AS DATE) AS month, last_day(CAST(o_orderdate AS DATE)) AS last FROM orders")
def op_date_arith(spark, sf):
    d = C("o_orderdate").cast("date")
    return table(spark, sf, "orders").select("o_orderkey", F.date_add(d, 30).alias("later"), F.trunc(d, "month").alias("month"), F.last_day(d).alias("last"))


@query("SELECT p_partkey, round(sin(p_size), 6) + 0.0 AS s, round(sqrt(p_retailprice), 6) AS r, round(ln(p_retailprice), 6) AS l, round(atan2(p_size, p_retailprice), 8) AS a, CAST(p_size % 7 AS INT) AS m, greatest(p_size, 25) AS g FROM part")
def op_math(spark, sf):
    s, r = C("p_size"), C("p_retailprice")
    return table(spark, sf, "part").select("p_partkey", _R(F.sin(s)).alias("s"), _R(F.sqrt(r)).alias("r"), _R(F.ln(r)).alias("l"), _R(F.atan2(s, r), 8).alias("a"), F.pmod(s, F.lit(7)).alias("m"), F.greatest(s, F.lit(25)).alias("g"))


@query("SELECT p_brand, CAST(sum(CAST(p_retailprice AS DECIMAL(18,2))) AS VARCHAR) AS total FROM part GROUP BY 1")
def op_decimal(spark, sf):
    return table(spark, sf, "part").groupBy("p_brand").agg(F.sum(C("p_retailprice").cast("decimal(18,2)")).cast("string").alias("total"))


@query("SELECT vec_id, round(list_sum([CAST(x AS DOUBLE) * CAST(x AS DOUBLE) FOR x IN embedding]), 5) AS norm, CAST(len([x FOR x IN embedding IF x > 0]) AS INT) AS positive FROM embeddings")
def op_array_hof(spark, sf):
    square = F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))
    return table(spark, sf, "embeddings").select("vec_id", _R(square, 5).alias("norm"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"))


@query("SELECT vec_id, round(sum(CAST(x AS DOUBLE)), 5) + 0.0 AS total FROM (SELECT vec_id, unnest(embedding) AS x FROM embeddings) GROUP BY 1")
def op_array_explode(spark, sf):
    e = table(spark, sf, "embeddings").select("vec_id", F.explode("embedding").alias("x"))
    return e.groupBy("vec_id").agg(_R(F.sum(C("x").cast("double")), 5).alias("total"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS a, CAST(json_extract_string(props, '$.k') AS INT) AS b, CAST(json_extract_string(props, '$.k') AS INT) AS c FROM events")
def op_json(spark, sf):
    return table(spark, sf, "events").select("event_id", F.from_json("props", "k int")["k"].alias("a"), F.get_json_object("props", "$.k").cast("int").alias("b"), F.variant_get(F.parse_json("props"), "$.k", "int").alias("c"))


@query("SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host FROM pages")
def op_url(spark, sf):
    return table(spark, sf, "pages").select("page_id", F.coalesce(F.try_parse_url("url", F.lit("HOST")), F.lit("")).alias("host"))


@query("SELECT doc_id, w AS word, count(*) AS n FROM (SELECT doc_id, unnest(string_split(text, ' ')) AS w FROM documents) GROUP BY ALL HAVING count(*) > 3")
def op_map(spark, sf):
    # texts move once; both aggregates then stay in the document's partition
    d = table(spark, sf, "documents").select("doc_id", "text").repartition("doc_id").select("doc_id", F.explode(F.split("text", " ")).alias("word")).groupBy("doc_id", "word").agg(F.count("*").alias("n"))
    m = d.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("word", "n"))).alias("m"))
    return m.select("doc_id", F.explode(F.map_filter("m", lambda k, v: v > 3)).alias("word", "n"))
