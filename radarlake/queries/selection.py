"""Scene selection, overview and product metadata on the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from radarlake.methods import overview, select
from radarlake.registry import query
from radarlake.standins import acquisitions, samples_fact, table, with_views

_RULES = "pol IN ('VV', 'HH') AND incidence_deg BETWEEN 10 AND 70 AND native_az_m BETWEEN 0.2::DOUBLE AND 2.0::DOUBLE AND native_rg_m BETWEEN 0.2::DOUBLE AND 2.0::DOUBLE"
_ENV = "CASE city_id % 4 WHEN 0 THEN 'urban' WHEN 1 THEN 'rural' WHEN 2 THEN 'coastal' ELSE 'mountain' END"
_R = lambda c, n=6: (F.round(c, n) + 0.0)


@query(with_views("acq", f"SELECT scene_id, city_id, country, pol, incidence_deg, round(native_az_m, 6) AS native_az_m FROM acq WHERE {_RULES}"))
def m1_select(spark, sf):
    return select.scenes(acquisitions(spark, sf)).select("scene_id", "city_id", "country", "pol", "incidence_deg", _R("native_az_m").alias("native_az_m"))


@query(with_views("acq", f"SELECT count(*) AS scenes, count(*) FILTER (pol NOT IN ('VV', 'HH')) AS fail_pol, count(*) FILTER (incidence_deg NOT BETWEEN 10 AND 70) AS fail_incidence, count(*) FILTER (native_az_m NOT BETWEEN 0.2::DOUBLE AND 2.0::DOUBLE) AS fail_spacing_az, count(*) FILTER (native_rg_m NOT BETWEEN 0.2::DOUBLE AND 2.0::DOUBLE) AS fail_spacing_rg, count(*) FILTER ({_RULES}) AS kept FROM acq"))
def m1_audit(spark, sf):
    return select.audit(acquisitions(spark, sf))


@query(with_views("acq", f"SELECT continent, {', '.join(f"count(*) FILTER (({_ENV}) = '{e}') AS {e}" for e in ('urban', 'rural', 'coastal', 'mountain'))} FROM acq WHERE {_RULES} GROUP BY continent"))
def m1_env(spark, sf):
    names = ["urban", "rural", "coastal", "mountain"]
    environment = F.element_at(F.array(*map(F.lit, names)), (F.col("city_id") % 4 + 1).cast("int"))
    return select.by_environment(select.scenes(acquisitions(spark, sf)), environment, names)


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")
def m1_props_parse(spark, sf):
    return table(spark, sf, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title, regexp_extract(html, '<html[^>]*lang=\"([^\"]*)\"', 1) AS lang, CAST(len(regexp_extract_all(html, '<a ')) AS INT) AS links FROM pages")
def m1_page_attrs(spark, sf):
    return table(spark, sf, "pages").select("page_id", F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"), F.regexp_extract("html", '<html[^>]*lang="([^"]*)"', 1).alias("lang"), F.regexp_count("html", F.lit("<a ")).alias("links"))


_TOP = """, counted AS (SELECT country, {agg} AS n FROM fact GROUP BY country), ranked AS (SELECT *, row_number() OVER (ORDER BY n DESC, country) AS rk FROM counted)
SELECT CASE WHEN rk <= 10 THEN country ELSE 'Other' END AS country, CAST(sum(n) AS BIGINT) AS n FROM ranked GROUP BY 1"""


@query(with_views("fact", _TOP.format(agg="count(*)")))
def m9_country(spark, sf):
    return overview.top_n(samples_fact(spark, sf), "country", 10)


@query(with_views("fact", _TOP.format(agg="count(DISTINCT city_id)")))
def m9_cities(spark, sf):
    return overview.top_n(samples_fact(spark, sf), "country", 10, distinct="city_id")


@query(with_views("fact", "SELECT count(*) AS samples, count(DISTINCT city_id) AS cities, count(DISTINCT country) AS countries, (SELECT round(max(n) / sum(n), 6) FROM (SELECT count(*) AS n FROM fact GROUP BY country)) AS leading_share FROM fact"))
def m9_coverage(spark, sf):
    return overview.coverage(samples_fact(spark, sf)).withColumn("leading_share", _R("leading_share"))


@query(with_views("fact", """, c AS (SELECT country, count(*) AS n FROM fact GROUP BY country), r AS (SELECT *, row_number() OVER (ORDER BY n DESC, country) AS rk, sum(n) OVER () AS total, count(*) OVER () AS k FROM c)
SELECT count(*) AS keys, round(1 - 2 * (sum((k - rk + 1.0::DOUBLE - 0.5) * 0 + n * (rk - 0.5::DOUBLE)) / max(total) / max(k)) , 6) AS gini,
(SELECT min(rk) FROM (SELECT rk, sum(n) OVER (ORDER BY rk) / total AS cum FROM r) WHERE cum >= 0.8) AS ranks_to_80 FROM r"""))
def m9_tail(spark, sf):
    return overview.tail(samples_fact(spark, sf), "country").withColumn("gini", _R("gini"))


@query(with_views("acq", "SELECT CAST(floor(lat0 / 10) * 10 AS INT) AS lat, CAST(floor(lon0 / 10) * 10 AS INT) AS lon, count(*) AS scenes FROM acq GROUP BY ALL"))
def m9_density(spark, sf):
    return overview.density(acquisitions(spark, sf), 10)


@query(with_views("fact", "SELECT continent, country, city_id, count(*) AS n, grouping(continent, country, city_id) AS level FROM fact GROUP BY ROLLUP (continent, country, city_id)"))
def m9_rollup(spark, sf):
    return overview.rollup(samples_fact(spark, sf), ["continent", "country", "city_id"])


@query(with_views("acq", "SELECT pol, CAST(floor(incidence_deg / 10) AS INT) AS band, count(*) AS n, grouping(pol, CAST(floor(incidence_deg / 10) AS INT)) AS level FROM acq GROUP BY CUBE (pol, CAST(floor(incidence_deg / 10) AS INT))"))
def m9_cube(spark, sf):
    banded = acquisitions(spark, sf).withColumn("band", F.floor(F.col("incidence_deg") / 10).cast("int"))
    return overview.cube(banded, ["pol", "band"])
