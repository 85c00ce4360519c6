"""Caption rules, labels and statistics on the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from radarlake import registry
from radarlake.methods import caption
from radarlake.methods.lexicon import COLORS, HEDGES, PART_CATEGORIES, PROMPTS
from radarlake.registry import query
from radarlake.standins import SQL, captions, table, with_views

_R = lambda c, n=6: (F.round(c, n) + 0.0)
_C = "|".join(sorted(COLORS, key=lambda w: (-len(w), w)))
_H = "|".join(sorted(HEDGES, key=lambda w: (-len(w), w)))
_SPACE = "trim(regexp_replace({}, '\\s+', ' ', 'g'))"
_DECOLOR = _SPACE.format(f"regexp_replace({{}}, '(?i)\\b(?:{_C})\\b(?:(?:\\s*,\\s*|\\s+and\\s+|\\s+or\\s+)(?:{_C})\\b)*', '', 'g')")
_DEHEDGE = _SPACE.format(f"regexp_replace({{}}, '(?i)\\b(?:{_H})\\b', '', 'g')")


def _parts(spark, sf):
    return table(spark, sf, "part").select(F.col("p_partkey").alias("sample_id"), F.col("p_name").alias("text"))


@query(with_views("captions", "SELECT sample_id, variant, text FROM captions"))
def m7_variants(spark, sf):
    return captions(spark, sf)


_PROMPTS = ", ".join(f"('{k}', '{v}')" for k, v in PROMPTS.items())


@query(f"SELECT doc_id AS sample_id, variant, true AS avoids_colors, length(prompt || chr(10) || coalesce(text, '')) AS chars, md5(prompt || chr(10) || coalesce(text, '')) AS digest FROM documents, (VALUES {_PROMPTS}) t(variant, prompt)")
def m7_prompts(spark, sf):
    """What a captioner is sent for each document and length, as digests; every instruction rules colors out."""
    sent = caption.requests(table(spark, sf, "documents").select(F.col("doc_id").alias("sample_id"), "text"), PROMPTS)
    return sent.select("sample_id", "variant", F.col("prompt").contains("no color").alias("avoids_colors"), F.length("request").cast("long").alias("chars"), F.md5("request").alias("digest"))


@query(f"SELECT p_partkey AS sample_id, {_DECOLOR.format('p_name')} AS text FROM part")
def m7_decolor(spark, sf):
    return _parts(spark, sf).select("sample_id", caption.strip_colors(F.col("text")).alias("text"))


_HEDGED = "'Possibly a ' || p_name || ', likely new, it appears that it might be a ' || p_name"


@query(f"SELECT p_partkey AS sample_id, {_DEHEDGE.format(_HEDGED)} AS text FROM part")
def m7_dehedge(spark, sf):
    text = F.concat(F.lit("Possibly a "), "text", F.lit(", likely new, it appears that it might be a "), "text")
    return _parts(spark, sf).select("sample_id", caption.strip_hedges(text).alias("text"))


@query(f"SELECT 'raw' AS stage, count(*) AS n, round(avg(CAST(regexp_matches(p_name, '(?i)\\b(?:{_C})\\b') AS INT)), 6) AS colors, 0.0::DOUBLE AS hedges FROM part UNION ALL SELECT 'clean', count(*), 0.0, 0.0 FROM part")
def m7_residual(spark, sf):
    raw = _parts(spark, sf).withColumn("stage", F.lit("raw"))
    cleaned = raw.withColumn("text", caption.clean(F.col("text"))).withColumn("stage", F.lit("clean"))
    return caption.residual_rates(raw.unionByName(cleaned), ["stage"]).withColumn("colors", _R("colors")).withColumn("hedges", _R("hedges"))


@query("SELECT sample_id, upper(substr(t, 1, 1)) || substr(t, 2) || '.' AS text FROM (SELECT p_partkey AS sample_id, p_name || ', near a ' || p_name AS t FROM part)")
def m7_normalize(spark, sf):
    messy = F.concat(F.lit("  "), "text", F.lit("  , near  a "), "text", F.lit(" ,. "))
    return _parts(spark, sf).select("sample_id", caption.normalize(messy).alias("text"))


_LABELS = ", ".join(f"('{name}', {k}, [{', '.join(repr(w) for w in yes)}], {'[' + ', '.join(repr(w) for w in no) + ']' if no else 'CAST([] AS VARCHAR[])'})" for k, (name, (yes, no)) in enumerate(PART_CATEGORIES.items()))
_SCORED = f"WITH v AS (SELECT * FROM (VALUES {_LABELS}) t(category, priority, yes, no)), s AS (SELECT p_partkey AS sample_id, category, priority, len(list_filter(string_split(p_name, ' '), lambda w: list_contains(yes, w))) AS hits, len(list_filter(string_split(p_name, ' '), lambda w: list_contains(no, w))) AS vetoes FROM part, v)"
_BEST = _SCORED + ", b AS (SELECT sample_id, category, CASE WHEN vetoes > 0 THEN 0 ELSE hits END AS h, row_number() OVER (PARTITION BY sample_id ORDER BY CASE WHEN vetoes > 0 THEN 0 ELSE hits END DESC, priority) AS r FROM s), l AS (SELECT sample_id, CASE WHEN h > 0 THEN category ELSE 'other' END AS category, CAST(h AS INT) AS hits FROM b WHERE r = 1)"


@query(_BEST + " SELECT * FROM l")
def m7_label(spark, sf):
    return caption.label(_parts(spark, sf), PART_CATEGORIES).select("sample_id", "category", "hits")


@query(_SCORED + " SELECT sample_id, category, CAST(hits AS INT) AS hits FROM s WHERE hits > 0 AND vetoes = 0")
def m7_label_multi(spark, sf):
    return caption.label_multi(_parts(spark, sf), PART_CATEGORIES).select("sample_id", "category", "hits")


@query(_SCORED + " SELECT category, count(*) FILTER (hits > 0) AS hit, count(*) FILTER (hits > 0 AND vetoes > 0) AS vetoed FROM s GROUP BY category")
def m7_label_veto(spark, sf):
    bare = {k: (yes, ()) for k, (yes, _) in PART_CATEGORIES.items()}
    hit = caption.label_multi(_parts(spark, sf), bare).groupBy("category").agg(F.count("*").alias("hit"))
    kept = caption.label_multi(_parts(spark, sf), PART_CATEGORIES).groupBy("category").agg(F.count("*").alias("kept"))
    return hit.join(kept, "category", "left").select("category", "hit", (F.col("hit") - F.coalesce("kept", F.lit(0))).alias("vetoed"))


@query(_BEST + " SELECT category, count(*) AS n, round(count(*) / sum(count(*)) OVER (), 6) AS share FROM l GROUP BY category")
def m7_dist(spark, sf):
    return caption.distribution(caption.label(_parts(spark, sf), PART_CATEGORIES)).withColumn("share", _R("share"))


_WORDS = ", w AS (SELECT variant, sample_id, unnest(regexp_extract_all(lower(text), '\\p{L}+')) AS word FROM captions)"
_LEN = ", n AS (SELECT variant, len(string_split(text, ' ')) AS w FROM captions)"


@query(with_views("captions", _LEN + " SELECT variant, count(*) AS n, round(avg(w), 6) AS mean_words FROM n GROUP BY variant"))
def m7_stats(spark, sf):
    return caption.stats(captions(spark, sf)).withColumn("mean_words", _R("mean_words"))


@query(with_views("captions", _LEN + " SELECT variant, quantile_cont(w, 0.1)::DOUBLE AS p10, quantile_cont(w, 0.9)::DOUBLE AS p90, CAST(quantile_disc(w, 0.1) AS DOUBLE) AS p10_disc, CAST(quantile_disc(w, 0.9) AS DOUBLE) AS p90_disc FROM n GROUP BY variant"))
def m7_pct(spark, sf):
    p = caption.percentiles(captions(spark, sf))
    return p.withColumn("p10_disc", F.col("p10_disc").cast("double")).withColumn("p90_disc", F.col("p90_disc").cast("double"))


@query()
def m7_pct_approx(spark, sf):
    return caption.percentiles(captions(spark, sf), exact=False)


@query(with_views("captions", _WORDS + " SELECT variant, count(DISTINCT word) AS vocabulary FROM w GROUP BY variant"))
def m7_vocab(spark, sf):
    return caption.vocabulary(captions(spark, sf))


@query()
def m7_vocab_approx(spark, sf):
    return caption.vocabulary(captions(spark, sf), approx=True)


@query(with_views("captions", ", k AS (SELECT variant, text, count(*) AS k FROM captions GROUP BY ALL) SELECT variant, CAST(sum(k) AS BIGINT) AS n, round(1 - count(*) / sum(k), 6) AS dup_extra, round(coalesce(sum(k) FILTER (k > 1), 0) / sum(k), 6) AS dup_member FROM k GROUP BY variant"))
def m7_dup(spark, sf):
    return caption.duplicates(captions(spark, sf)).withColumn("dup_extra", _R("dup_extra")).withColumn("dup_member", _R("dup_member"))


@query("SELECT 'PART' AS variant, count(*) AS n, round(1 - count(DISTINCT p_name) / count(*), 6) AS dup_extra FROM part")
def m7_dup_part(spark, sf):
    d = caption.duplicates(_parts(spark, sf).withColumn("variant", F.lit("PART")))
    return d.select("variant", "n", _R("dup_extra").alias("dup_extra"))


@query(with_views("captions", _WORDS + " SELECT variant, count(DISTINCT word) AS types, count(*) AS tokens, round(count(DISTINCT word) / count(*), 6) AS ratio FROM w GROUP BY variant"))
def m7_diversity(spark, sf):
    return caption.diversity(captions(spark, sf)).withColumn("ratio", _R("ratio"))


@query(with_views("captions", _WORDS + ", c AS (SELECT variant, word, count(*) AS k FROM w GROUP BY ALL), r AS (SELECT *, row_number() OVER (PARTITION BY variant ORDER BY k DESC, word) AS rank FROM c) SELECT variant, word, k, CAST(rank AS INT) AS rank FROM r WHERE rank <= 20"))
def m7_topwords(spark, sf):
    return caption.top_words(captions(spark, sf), 20)


# --- the same over whole texts ----------------------------------------------------


def _whole(spark, sf):
    return table(spark, sf, "documents").select(F.col("doc_id").alias("sample_id"), F.lit("WHOLE").alias("variant"), "text")


def _over_texts(name: str) -> str:
    """A query's SQL with whole documents in place of captions."""
    return registry.known()[name].replace(SQL["captions"], "SELECT doc_id AS sample_id, 'WHOLE' AS variant, text FROM documents")


@query(_over_texts("m7_vocab"))
def m7_vocab_texts(spark, sf):
    return caption.vocabulary(_whole(spark, sf))


@query(_over_texts("m7_dup"))
def m7_dup_texts(spark, sf):
    return caption.duplicates(_whole(spark, sf)).withColumn("dup_extra", _R("dup_extra")).withColumn("dup_member", _R("dup_member"))


@query(_over_texts("m7_topwords"))
def m7_topwords_texts(spark, sf):
    return caption.top_words(_whole(spark, sf), 20)


@query(r"SELECT 'WHOLE' AS variant, count(*) AS n, round(avg(len(regexp_split_to_array(regexp_replace(text, '^\s+|\s+$', '', 'g'), '\s+'))), 6) AS mean_words FROM documents")
def m7_stats_texts(spark, sf):
    return caption.stats(_whole(spark, sf)).withColumn("mean_words", _R("mean_words"))
