"""Splits, shards, audits and licences on the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from radarlake.methods import release
from radarlake.registry import query
from radarlake.standins import captions, samples_fact, table, with_views

_R = lambda c, n=6: (F.round(c, n) + 0.0)
_BUCKET = "CAST('0x' || substr(md5(CAST({} AS VARCHAR)), 1, 8) AS BIGINT) % 10000"
_NAME = "CASE WHEN {0} < 0.8 THEN 'train' WHEN {0} < 0.9 THEN 'validation' ELSE 'test' END"
_SPLIT = _NAME.format(f"{_BUCKET.format('{0}')} / 10000.0")


def _doc_samples(spark, sf):
    d = table(spark, sf, "documents").select("doc_id", "text", "source", F.octet_length("text").cast("long").alias("bytes"))
    return release.split(d, "source").withColumn("key", release.key("source", "doc_id"))


_DOCS = f"d AS (SELECT doc_id, text, source, CAST(strlen(text) AS BIGINT) AS bytes, {_SPLIT.format('source')} AS split, md5(source || '-' || doc_id) AS key FROM documents)"


@query(f"WITH {_DOCS} SELECT count(*) AS samples, count(DISTINCT key) AS keys, min(key) AS first FROM d")
def m8_key(spark, sf):
    return _doc_samples(spark, sf).agg(F.count("*").alias("samples"), F.count_distinct("key").alias("keys"), F.min("key").alias("first"))


@query(with_views("fact", f"SELECT {_SPLIT.format('scene_id')} AS split, count(DISTINCT scene_id) AS passes, count(*) AS samples FROM fact GROUP BY 1"))
def m8_split(spark, sf):
    return release.split(samples_fact(spark, sf), "scene_id").groupBy("split").agg(F.count_distinct("scene_id").alias("passes"), F.count("*").alias("samples"))


@query(with_views("fact", f", n AS (SELECT scene_id, count(*) AS n FROM fact GROUP BY 1), r AS (SELECT *, sum(n) OVER (ORDER BY md5(CAST(scene_id AS VARCHAR)), scene_id) - n AS before, sum(n) OVER () AS total FROM n) SELECT scene_id, n, {_NAME.format('before / total')} AS split FROM r"))
def m8_split_bal(spark, sf):
    return release.split_balanced(samples_fact(spark, sf), "scene_id")


@query(with_views("fact", f", n AS (SELECT DISTINCT scene_id, continent FROM fact), r AS (SELECT *, (row_number() OVER (PARTITION BY continent ORDER BY md5(CAST(scene_id AS VARCHAR)), scene_id) - 1) / count(*) OVER (PARTITION BY continent) AS share FROM n) SELECT continent, {_NAME.format('share')} AS split, count(*) AS passes FROM r GROUP BY ALL"))
def m8_split_strat(spark, sf):
    return release.split_stratified(samples_fact(spark, sf), "scene_id", "continent").groupBy("continent", "split").agg(F.count("*").alias("passes"))


def _leak(name: str, by: str):
    sql = with_views("fact", f", s AS (SELECT *, {_SPLIT.format('scene_id')} AS split FROM fact), n AS (SELECT {by}, count(DISTINCT split) AS k FROM s GROUP BY 1) SELECT count(*) AS values, count(*) FILTER (k > 1) AS leaking FROM n")
    query(sql, name)(lambda spark, sf: release.leakage(release.split(samples_fact(spark, sf), "scene_id"), by))


_leak("m8_leak_pass", "scene_id")
_leak("m8_leak_city", "city_id")


@query(f"WITH {_DOCS}, n AS (SELECT md5(text) AS h, count(DISTINCT split) AS k FROM d GROUP BY 1) SELECT count(*) AS values, count(*) FILTER (k > 1) AS leaking FROM n")
def m8_leak_text(spark, sf):
    return release.leakage(_doc_samples(spark, sf).withColumn("h", F.md5("text")), "h")


_SAMPLE = "l_orderkey || '-' || l_partkey || '-' || l_suppkey || '-' || l_linenumber"


@query(with_views("fact", f", s AS (SELECT *, {_NAME.format(_BUCKET.format(_SAMPLE) + ' / 10000.0')} AS split FROM fact), n AS (SELECT scene_id, count(DISTINCT split) AS k FROM s GROUP BY 1) SELECT count(*) AS values, count(*) FILTER (k > 1) AS leaking FROM n"))
def b_random_split(spark, sf):
    return release.leakage(release.split_random(samples_fact(spark, sf), "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"), "scene_id")


@query(f"WITH {_DOCS}, r AS (SELECT *, CAST(sum(bytes) OVER (PARTITION BY split ORDER BY key) AS BIGINT) - bytes AS before FROM d) SELECT key, split, before // 100000 AS shard, before // 100000 // 4 AS chunk, split || '/chunk_' || (before // 100000 // 4) || '/shard-' || (before // 100000) || '.tar' AS path FROM r")
def m8_shards(spark, sf):
    return release.shards(_doc_samples(spark, sf), 100_000, per_chunk=4).select("key", "split", "shard", "chunk", "path")


@query(f"WITH {_DOCS} SELECT doc_id, '{{\"key\":\"' || key || '\",\"split\":\"' || split || '\",\"bytes\":' || bytes || '}}' AS meta FROM d")
def m8_meta_json(spark, sf):
    return _doc_samples(spark, sf).select("doc_id", F.to_json(F.struct("key", "split", "bytes")).alias("meta"))


@query(f"WITH {_DOCS}, r AS (SELECT key, row_number() OVER (PARTITION BY split ORDER BY md5('7' || key)) AS place, split FROM d) SELECT key, split, CAST(place AS INT) AS place FROM r")
def m8_shuffle(spark, sf):
    return release.shuffled(_doc_samples(spark, sf).select("key", "split"), 7).select("key", "split", "place")


_MEMBERS = "m AS (SELECT doc_id, component, CASE component WHEN 'radar' THEN n_chars * 8 WHEN 'metadata' THEN 512 WHEN 'captions' THEN n_chars ELSE n_chars * 3 END AS bytes FROM documents, (VALUES ('radar'), ('metadata'), ('captions'), ('optical')) t(component))"


def _members(spark, sf):
    d = table(spark, sf, "documents").select("doc_id", "n_chars", F.explode(F.array(*map(F.lit, ("radar", "metadata", "captions", "optical")))).alias("component"))
    size = F.when(F.col("component") == "radar", F.col("n_chars") * 8).when(F.col("component") == "metadata", F.lit(512)).when(F.col("component") == "captions", F.col("n_chars")).otherwise(F.col("n_chars") * 3)
    return d.select("doc_id", "component", size.cast("long").alias("bytes"))


@query(f"WITH {_MEMBERS} SELECT doc_id, component, CAST(bytes AS BIGINT) AS bytes, 'CC-BY-4.0' AS attribution FROM m WHERE component <> 'optical'")
def m8_license(spark, sf):
    return release.license_filter(_members(spark, sf)).select("doc_id", "component", "bytes", "attribution")


@query(f"WITH {_MEMBERS} SELECT component, count(*) AS members, CAST(sum(bytes) AS BIGINT) AS bytes FROM m GROUP BY component")
def m8_volume(spark, sf):
    return release.volume(_members(spark, sf))


_RUNS = "SELECT {k}, unnest(list_distinct([array_to_string(w[i:i+7], ' ') FOR i IN range(1, len(w) - 6)])) AS h FROM (SELECT {k}, regexp_split_to_array(regexp_replace(lower(text), '^\\s+|\\s+$', '', 'g'), '\\s+') AS w FROM {t})"


@query(f"WITH a AS ({_RUNS.format(k='doc_id', t='documents')}), b AS ({_RUNS.format(k='item_id', t='benchmark')}) SELECT doc_id, item_id, count(*) AS shared FROM a JOIN b USING (h) GROUP BY ALL")
def m8_contam(spark, sf):
    return release.contamination(table(spark, sf, "documents"), table(spark, sf, "benchmark"))


@query(with_views("captions", f", s AS (SELECT c.variant, md5(c.text) AS h, {_SPLIT.format('d.source')} AS split FROM captions c JOIN documents d ON d.doc_id = c.sample_id), n AS (SELECT variant, h, count(DISTINCT split) AS k FROM s GROUP BY ALL) SELECT variant, count(*) AS texts, count(*) FILTER (k > 1) AS leaking FROM n GROUP BY variant"))
def m8_leak_captions(spark, sf):
    s = captions(spark, sf).join(_doc_samples(spark, sf).select(F.col("doc_id").alias("sample_id"), "split"), "sample_id")
    n = s.groupBy("variant", F.md5("text").alias("h")).agg(F.count_distinct("split").alias("k"))
    return n.groupBy("variant").agg(F.count("*").alias("texts"), F.count_if(F.col("k") > 1).alias("leaking"))
