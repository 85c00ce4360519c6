"""The relational surface around the methods: joins, aggregates, windows, sets, subqueries."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from radarlake.registry import query
from radarlake.standins import acquisitions, table, with_views

_R = lambda c, n=4: (F.round(c, n) + 0.0)
C = F.col


def _t(spark, sf, name):
    return table(spark, sf, name)


@query("SELECT o_orderkey, o_custkey, o_totalprice FROM orders WHERE o_orderdate >= DATE '1998-01-01' AND o_totalprice > 100000")
def op_scan_pruned(spark, sf):
    return _t(spark, sf, "orders").filter((C("o_orderdate") >= F.lit("1998-01-01").cast("timestamp_ntz")) & (C("o_totalprice") > 100000)).select("o_orderkey", "o_custkey", "o_totalprice")


@query(with_views("acq", "SELECT scene_id, lat0, lon0 FROM acq WHERE lat0 BETWEEN -10 AND 40 AND (lon0 >= 170 OR lon0 <= -160)"))
def op_filter_box(spark, sf):
    return acquisitions(spark, sf).filter(C("lat0").between(-10, 40) & ((C("lon0") >= 170) | (C("lon0") <= -160))).select("scene_id", "lat0", "lon0")


@query("SELECT d.doc_id, l.quality IS NOT DISTINCT FROM 1 AS good FROM documents d LEFT JOIN labels l USING (doc_id)")
def op_nullsafe(spark, sf):
    return _t(spark, sf, "documents").join(_t(spark, sf, "labels"), "doc_id", "left").select("doc_id", C("quality").eqNullSafe(1).alias("good"))


@query("SELECT count(*) FILTER (text LIKE '%the%') AS has_the, count(*) FILTER (regexp_matches(text, '[0-9]{3}')) AS has_digits, count(*) FILTER (starts_with(text, 'A')) AS starts_a FROM documents")
def op_like(spark, sf):
    return _t(spark, sf, "documents").agg(F.count_if(C("text").like("%the%")).alias("has_the"), F.count_if(C("text").rlike("[0-9]{3}")).alias("has_digits"), F.count_if(C("text").startswith("A")).alias("starts_a"))


@query("SELECT event_id, user_id FROM events WHERE event_type IN ('error', 'purchase') AND user_id IN (1, 2, 3, 5, 8)")
def op_in_list(spark, sf):
    return _t(spark, sf, "events").filter(C("event_type").isin("error", "purchase") & C("user_id").isin(1, 2, 3, 5, 8)).select("event_id", "user_id")


@query("SELECT l_orderkey AS order_key, CAST(l_quantity AS INT) AS quantity, round(sum(l_extendedprice * (1 - l_discount)) + 1e-6, 3) AS net FROM lineitem GROUP BY ALL")
def op_project_expr(spark, sf):
    p = _t(spark, sf, "lineitem").select(C("l_orderkey").alias("order_key"), C("l_quantity").cast("int").alias("quantity"), (C("l_extendedprice") * (1 - C("l_discount"))).alias("net"))
    return p.groupBy("order_key", "quantity").agg(_R(F.sum("net") + 1e-6, 3).alias("net"))


_INNER = "SELECT o_orderstatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"


def _inner(spark, sf, hint=None):
    o = _t(spark, sf, "orders")
    j = _t(spark, sf, "lineitem").join(o.hint(hint) if hint else o, C("l_orderkey") == C("o_orderkey"))
    return j.groupBy("o_orderstatus").agg(F.count("*").alias("n"), _R(F.sum("l_quantity"), 2).alias("quantity"))


@query(_INNER)
def op_join_inner(spark, sf):
    return _inner(spark, sf)


@query(_INNER)
def op_join_hash(spark, sf):
    return _inner(spark, sf, "shuffle_hash")


@query("SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def op_join_broadcast(spark, sf):
    j = _t(spark, sf, "customer").join(F.broadcast(_t(spark, sf, "nation")), C("c_nationkey") == C("n_nationkey")).join(F.broadcast(_t(spark, sf, "region")), C("n_regionkey") == C("r_regionkey"))
    return j.groupBy("r_name").agg(F.count("*").alias("n"))


@query("SELECT d.doc_id, l.quality, l.toxic FROM documents d LEFT JOIN labels l USING (doc_id)")
def op_join_left(spark, sf):
    return _t(spark, sf, "documents").join(_t(spark, sf, "labels"), "doc_id", "left").select("doc_id", "quality", "toxic")


@query("SELECT l.doc_id, d.lang FROM (SELECT * FROM documents WHERE lang = 'en') d RIGHT JOIN labels l ON d.doc_id = l.doc_id")
def op_join_right(spark, sf):
    return _t(spark, sf, "documents").filter("lang = 'en'").join(_t(spark, sf, "labels"), "doc_id", "right").select("doc_id", "lang")


@query("SELECT coalesce(c.k, s.k) AS nation, c.n AS customers, s.n AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer WHERE c_acctbal < 0 GROUP BY 1) c FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier WHERE s_acctbal < 1000 GROUP BY 1) s ON c.k = s.k")
def op_join_full(spark, sf):
    c = _t(spark, sf, "customer").filter("c_acctbal < 0").groupBy(C("c_nationkey").alias("nation")).agg(F.count("*").alias("customers"))
    s = _t(spark, sf, "supplier").filter("s_acctbal < 1000").groupBy(C("s_nationkey").alias("nation")).agg(F.count("*").alias("suppliers"))
    return c.join(s, "nation", "full")


@query("SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_discount > 0.05)")
def op_join_semi(spark, sf):
    return _t(spark, sf, "orders").join(_t(spark, sf, "lineitem").filter("l_discount > 0.05D"), C("o_orderkey") == C("l_orderkey"), "left_semi").select("o_orderkey")


@query("SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def op_join_anti(spark, sf):
    return _t(spark, sf, "orders").join(_t(spark, sf, "lineitem"), C("o_orderkey") == C("l_orderkey"), "left_anti").select("o_orderkey")


@query("SELECT r_name, label, count(vec_id) AS n FROM region CROSS JOIN (SELECT DISTINCT label FROM embeddings) LEFT JOIN embeddings USING (label) GROUP BY ALL")
def op_join_cross(spark, sf):
    e = _t(spark, sf, "embeddings").select("vec_id", "label")
    grid = _t(spark, sf, "region").select("r_name").crossJoin(F.broadcast(e.select("label").distinct()))
    return grid.join(e, "label", "left").groupBy("r_name", "label").agg(F.count("vec_id").alias("n"))


@query("SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey")
def op_join_theta(spark, sf):
    n = _t(spark, sf, "nation")
    return n.alias("x").join(n.alias("y"), (C("x.n_nationkey") < C("y.n_nationkey")) & (C("x.n_regionkey") == C("y.n_regionkey"))).select(C("x.n_name").alias("a"), C("y.n_name").alias("b"))


@query("SELECT a.o_custkey, count(*) AS pairs FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND a.o_orderkey < b.o_orderkey AND abs(date_diff('day', CAST(a.o_orderdate AS DATE), CAST(b.o_orderdate AS DATE))) <= 365 GROUP BY 1")
def op_join_self(spark, sf):
    o = _t(spark, sf, "orders").select("o_custkey", "o_orderkey", "o_orderdate")
    j = o.alias("a").join(o.alias("b"), (C("a.o_custkey") == C("b.o_custkey")) & (C("a.o_orderkey") < C("b.o_orderkey")) & (F.abs(F.datediff("a.o_orderdate", "b.o_orderdate")) <= 365))
    return j.groupBy(C("a.o_custkey").alias("o_custkey")).agg(F.count("*").alias("pairs"))


@query("SELECT a.event_id, count(*) AS follow FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE WHERE a.event_type = 'error' GROUP BY 1")
def op_join_interval(spark, sf):
    e = _t(spark, sf, "events").select("event_id", "user_id", "ts", "event_type")
    j = e.filter("event_type = 'error'").alias("a").join(e.alias("b"), (C("a.user_id") == C("b.user_id")) & (C("b.ts") > C("a.ts")) & (C("b.ts") <= C("a.ts") + F.expr("INTERVAL 30 MINUTES")))
    return j.groupBy(C("a.event_id").alias("event_id")).agg(F.count("*").alias("follow"))


@query("SELECT e.event_id, p.event_id AS purchase_id FROM (SELECT * FROM events WHERE event_type = 'error') e ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'purchase' GROUP BY ALL) p ON e.user_id = p.user_id AND e.ts >= p.ts")
def op_join_asof(spark, sf):
    """Both sides in one sort by user and time; the latest purchase carries forward."""
    e = _t(spark, sf, "events").filter(C("event_type").isin("error", "purchase"))
    is_purchase = C("event_type") == "purchase"
    order = Window.partitionBy("user_id").orderBy("ts", F.desc(is_purchase), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    latest = e.withColumn("purchase_id", F.last(F.when(is_purchase, C("event_id")), ignorenulls=True).over(order))
    return latest.filter(~is_purchase).select("event_id", "purchase_id")


@query("SELECT o_custkey, o_orderkey, o_totalprice FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r = 1")
def op_join_lateral(spark, sf):
    return _t(spark, sf, "orders").groupBy("o_custkey").agg(F.max_by(F.struct("o_orderkey", "o_totalprice"), F.struct("o_totalprice", -C("o_orderkey"))).alias("b")).select("o_custkey", "b.*")


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity, round(avg(l_extendedprice), 4) AS price, min(l_discount) + 0.0 AS lo, max(l_tax) + 0.0 AS hi FROM lineitem GROUP BY ALL")
def op_agg_basic(spark, sf):
    return _t(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), _R(F.sum("l_quantity"), 2).alias("quantity"), _R(F.avg("l_extendedprice")).alias("price"), (F.min("l_discount") + 0.0).alias("lo"), (F.max("l_tax") + 0.0).alias("hi"))


@query("SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")
def op_agg_distinct(spark, sf):
    return _t(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_suppkey").alias("suppliers"), F.count_distinct("l_partkey").alias("parts"))


@query("SELECT event_type, count(*) FILTER (value > 100) AS large, round(sum(CASE WHEN value > 100 THEN value ELSE 0 END), 2) AS total FROM events GROUP BY 1")
def op_agg_cond(spark, sf):
    return _t(spark, sf, "events").groupBy("event_type").agg(F.count_if(C("value") > 100).alias("large"), _R(F.sum(F.when(C("value") > 100, C("value")).otherwise(0.0)), 2).alias("total"))


@query("SELECT l_returnflag, round(var_samp(l_quantity), 4) AS var, round(stddev_pop(l_tax), 6) AS dev, round(corr(l_quantity, l_extendedprice), 6) AS corr, round(regr_slope(l_extendedprice, l_quantity), 3) AS slope FROM lineitem GROUP BY 1")
def op_agg_stats(spark, sf):
    return _t(spark, sf, "lineitem").groupBy("l_returnflag").agg(_R(F.var_samp("l_quantity")).alias("var"), _R(F.stddev_pop("l_tax"), 6).alias("dev"), _R(F.corr("l_quantity", "l_extendedprice"), 6).alias("corr"), _R(F.regr_slope("l_extendedprice", "l_quantity"), 3).alias("slope"))


@query("SELECT event_type, round(quantile_cont(value, 0.25), 6) AS q1, round(median(value), 6) AS med FROM events GROUP BY 1")
def op_agg_pct(spark, sf):
    return _t(spark, sf, "events").groupBy("event_type").agg(_R(F.percentile("value", F.lit(0.25)), 6).alias("q1"), _R(F.median("value"), 6).alias("med"))


@query("SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
def op_agg_collect(spark, sf):
    return _t(spark, sf, "nation").groupBy("n_regionkey").agg(F.concat_ws(",", F.sort_array(F.collect_set("n_name"))).alias("names"))


@query("SELECT user_id, arg_max(event_id, value * 1000000 + event_id) AS best FROM events GROUP BY 1")
def op_agg_argmax(spark, sf):
    return _t(spark, sf, "events").groupBy("user_id").agg(F.max_by("event_id", C("value") * 1000000 + C("event_id")).alias("best"))


@query()
def op_agg_approx(spark, sf):
    return _t(spark, sf, "lineitem").agg(F.approx_count_distinct("l_orderkey", 0.02).alias("orders"), F.percentile_approx("l_quantity", F.lit(0.5), F.lit(1000)).alias("median"))


@query("SELECT CAST(ts AS DATE) AS day, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'error') AS error FROM events WHERE event_type IN ('click', 'error') GROUP BY 1")
def op_agg_pivot(spark, sf):
    e = _t(spark, sf, "events").filter(C("event_type").isin("click", "error")).withColumn("day", C("ts").cast("date"))
    return e.groupBy("day").pivot("event_type", ["click", "error"]).count().na.fill(0)


@query("SELECT p_partkey, 'size' AS k, CAST(p_size AS DOUBLE) AS v FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")
def op_agg_unpivot(spark, sf):
    p = _t(spark, sf, "part").select("p_partkey", C("p_size").cast("double").alias("size"), C("p_retailprice").alias("price"))
    return p.unpivot("p_partkey", ["size", "price"], "k", "v")


@query(with_views("acq", "SELECT continent, pol, count(*) AS n, grouping(continent, pol) AS level FROM acq GROUP BY ROLLUP (continent, pol)"))
def op_agg_rollup(spark, sf):
    return acquisitions(spark, sf).rollup("continent", "pol").agg(F.count("*").alias("n"), F.grouping_id().alias("level"))


@query(with_views("acq", "SELECT continent, pol, count(*) AS n FROM acq GROUP BY GROUPING SETS ((continent), (pol))"))
def op_agg_gsets(spark, sf):
    return acquisitions(spark, sf).groupingSets([["continent"], ["pol"]], "continent", "pol").agg(F.count("*").alias("n"))


@query("SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 12")
def op_agg_having(spark, sf):
    return _t(spark, sf, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).filter("n > 12")


@query("SELECT CASE WHEN l_suppkey % 3 = 0 THEN 0 ELSE l_suppkey END AS k, count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem GROUP BY 1")
def op_agg_salted(spark, sf):
    """A third of the rows have one key: salted sums first, then the sums of those."""
    s = _t(spark, sf, "lineitem").withColumn("k", F.when(C("l_suppkey") % 3 == 0, F.lit(0)).otherwise(C("l_suppkey"))).withColumn("salt", F.pmod(F.hash("l_orderkey"), F.lit(16)))
    one = s.groupBy("k", "salt").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("q"))
    return one.groupBy("k").agg(F.sum("n").alias("n"), _R(F.sum("q"), 2).alias("q"))


def _orders():
    return Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")


@query("SELECT o_orderkey, CAST(row_number() OVER w AS INT) AS rn, CAST(rank() OVER w AS INT) AS rk, round(percent_rank() OVER w, 6) AS pr, CAST(ntile(4) OVER w AS INT) AS nt FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)")
def op_win_rank(spark, sf):
    return _t(spark, sf, "orders").select("o_orderkey", F.row_number().over(_orders()).alias("rn"), F.rank().over(_orders()).alias("rk"), _R(F.percent_rank().over(_orders()), 6).alias("pr"), F.ntile(4).over(_orders()).alias("nt"))


@query("SELECT o_orderkey, lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)")
def op_win_analytic(spark, sf):
    return _t(spark, sf, "orders").select("o_orderkey", F.lag("o_orderkey").over(_orders()).alias("before"), F.lead("o_orderkey").over(_orders()).alias("after"))


@query("SELECT o_orderkey, round(avg(o_totalprice) OVER (w ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING), 4) AS moving FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)")
def op_win_rows(spark, sf):
    return _t(spark, sf, "orders").select("o_orderkey", _R(F.avg("o_totalprice").over(_orders().rowsBetween(-1, 1))).alias("moving"))


@query("SELECT user_id, count(*) AS sessions FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events) WHERE p IS NULL OR ts > p + INTERVAL 30 MINUTE GROUP BY 1")
def op_win_sessionise(spark, sf):
    p = F.lag("ts").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    e = _t(spark, sf, "events").withColumn("p", p).filter(C("p").isNull() | (C("ts") > C("p") + F.expr("INTERVAL 30 MINUTES")))
    return e.groupBy("user_id").agg(F.count("*").alias("sessions"))


@query("SELECT o_orderkey, round(o_totalprice / sum(o_totalprice) OVER (PARTITION BY o_custkey), 8) AS share FROM orders")
def op_win_share(spark, sf):
    return _t(spark, sf, "orders").select("o_orderkey", _R(C("o_totalprice") / F.sum("o_totalprice").over(Window.partitionBy("o_custkey")), 8).alias("share"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def op_topk(spark, sf):
    return _t(spark, sf, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 20")
def op_offset(spark, sf):
    return _t(spark, sf, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(20).limit(20).select("o_orderkey", "o_totalprice")


@query("SELECT 'customer' AS kind, c_nationkey AS nation FROM customer UNION ALL SELECT 'supplier', s_nationkey FROM supplier")
def op_union_byname(spark, sf):
    s = _t(spark, sf, "supplier").select(C("s_nationkey").alias("nation"), F.lit("supplier").alias("kind"))
    return _t(spark, sf, "customer").select(F.lit("customer").alias("kind"), C("c_nationkey").alias("nation")).unionByName(s)


@query("SELECT c_nationkey AS nation FROM customer INTERSECT SELECT s_nationkey FROM supplier WHERE s_acctbal < 500")
def op_intersect(spark, sf):
    return _t(spark, sf, "customer").select(C("c_nationkey").alias("nation")).intersect(_t(spark, sf, "supplier").filter("s_acctbal < 500").select("s_nationkey"))


@query("SELECT n_nationkey AS nation FROM nation EXCEPT SELECT s_nationkey FROM supplier WHERE s_acctbal < 500")
def op_except(spark, sf):
    return _t(spark, sf, "nation").select(C("n_nationkey").alias("nation")).exceptAll(_t(spark, sf, "supplier").filter("s_acctbal < 500").select("s_nationkey").distinct())


@query("SELECT min(doc_id) AS doc_id FROM documents GROUP BY text")
def op_dedup(spark, sf):
    return _t(spark, sf, "documents").groupBy(F.sha2("text", 256).alias("h")).agg(F.min("doc_id").alias("doc_id")).select("doc_id")


@query("SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)")
def op_scalar_sub(spark, sf):
    o = _t(spark, sf, "orders")
    return o.crossJoin(F.broadcast(o.agg((F.avg("o_totalprice") * 1.5).alias("a")))).filter(C("o_totalprice") > C("a")).select("o_orderkey")


@query("SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 450000)")
def op_exists(spark, sf):
    return _t(spark, sf, "customer").join(_t(spark, sf, "orders").filter("o_totalprice > 450000"), C("c_custkey") == C("o_custkey"), "left_semi").select("c_custkey")


@query("SELECT c_custkey FROM customer c WHERE NOT EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 450000)")
def op_not_exists(spark, sf):
    return _t(spark, sf, "customer").join(_t(spark, sf, "orders").filter("o_totalprice > 450000"), C("c_custkey") == C("o_custkey"), "left_anti").select("c_custkey")


@query("SELECT l_orderkey, count(*) AS n FROM lineitem WHERE CAST('0x' || substr(md5(CAST(l_orderkey AS VARCHAR)), 1, 8) AS BIGINT) % 10000 < 1000 GROUP BY 1")
def op_sample_hash(spark, sf):
    from radarlake.methods.release import bucket

    return _t(spark, sf, "lineitem").filter(bucket(C("l_orderkey")) < 1000).groupBy("l_orderkey").agg(F.count("*").alias("n"))


@query("SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS hour, event_type, count(*) AS n FROM events GROUP BY ALL")
def op_win_tumbling(spark, sf):
    w = _t(spark, sf, "events").groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n"))
    return w.select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("hour"), "event_type", "n")
