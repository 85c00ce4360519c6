"""Speckle, representations and retrieval on the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from radarlake.methods import evaluate, physics
from radarlake.registry import query
from radarlake.standins import scene_cells, scenes, table, vec_patches, with_views

_R = lambda c, n=6: (F.round(c, n) + 0.0)
_I = ", i AS (SELECT *, re * re + im * im AS i FROM cells)"


@query(with_views("patches", "SELECT patch_id, r, c, round(sqrt(re * re + im * im), 6) AS amplitude, round(re * re + im * im, 8) AS intensity, round(10 * log10(re * re + im * im), 5) AS db, round(atan2(im, re), 6) + 0.0 AS phase FROM patches"))
def m10_repr(spark, sf):
    p = vec_patches(spark, sf)
    kinds = {"amplitude": 6, "intensity": 8, "db": 5, "phase": 6}
    return p.select("patch_id", "r", "c", *(_R(physics.represent(k), n).alias(k) for k, n in kinds.items()))


@query(with_views("cells", _I + " SELECT scene_id, round(avg(i) * avg(i) / var_samp(i), 6) AS enl FROM i GROUP BY 1"))
def m10_enl(spark, sf):
    return physics.enl(scene_cells(spark, sf), ["scene_id"]).select("scene_id", _R("enl").alias("enl"))


@query(with_views("cells", _I + " SELECT scene_id, CAST(r // 6 AS INT) AS tr, CAST(c // 6 AS INT) AS tc, round(avg(i) * avg(i) / var_samp(i), 5) AS enl FROM i GROUP BY ALL"))
def m10_enl_tile(spark, sf):
    c = scene_cells(spark, sf).withColumn("tr", F.floor(F.col("r") / 6).cast("int")).withColumn("tc", F.floor(F.col("c") / 6).cast("int"))
    return physics.enl(c, ["scene_id", "tr", "tc"]).select("scene_id", "tr", "tc", _R("enl", 5).alias("enl"))


@query(with_views("cells", _I + ", l AS (SELECT scene_id, ln(i) AS y FROM i WHERE i > 0), m AS (SELECT scene_id, avg(y) AS k1 FROM l GROUP BY 1) SELECT scene_id, count(*) AS n, round(avg(k1), 6) AS k1, round(avg((y - k1) ** 2), 6) AS k2, round(avg((y - k1) ** 3), 5) + 0.0 AS k3 FROM l JOIN m USING (scene_id) GROUP BY 1"))
def m10_logcum(spark, sf):
    k = physics.log_cumulants(scene_cells(spark, sf), ["scene_id"])
    return k.select("scene_id", "n", _R("k1").alias("k1"), _R("k2").alias("k2"), _R("k3", 5).alias("k3"))


@query(with_views("cells", ", n AS (SELECT a.scene_id, a.r, a.c, avg(b.re * b.re + b.im * b.im) AS m FROM cells a JOIN cells b ON a.scene_id = b.scene_id AND abs(a.r - b.r) <= 1 AND abs(a.c - b.c) <= 1 GROUP BY ALL) SELECT scene_id, r, c, round(m + 3e-6, 2) AS intensity FROM n"))
def m10_multilook(spark, sf):
    return physics.multilook(scene_cells(spark, sf), 1).select("scene_id", "r", "c", _R(F.col("mean") + 3e-6, 2).alias("intensity"))


@query(with_views("cells", ", n AS (SELECT a.scene_id, a.r, a.c, avg(b.re * b.re + b.im * b.im) AS m, var_pop(b.re * b.re + b.im * b.im) AS v, max(a.re * a.re + a.im * a.im) AS i FROM cells a JOIN cells b ON a.scene_id = b.scene_id AND abs(a.r - b.r) <= 1 AND abs(a.c - b.c) <= 1 GROUP BY ALL) SELECT scene_id, r, c, round(CASE WHEN v = 0 THEN m ELSE m + greatest(0, 1 - m * m / 4 / v) * (i - m) END, 1) AS intensity FROM n"))
def m10_lee(spark, sf):
    return physics.lee(scene_cells(spark, sf), 1, 4).select("scene_id", "r", "c", _R("filtered", 1).alias("intensity"))


_Q = ", q AS (SELECT vec_id, label, embedding FROM embeddings WHERE vec_id % 50 = 0), c AS (SELECT vec_id, label, embedding FROM embeddings), s AS (SELECT q.vec_id AS query, c.vec_id AS hit, q.label AS ql, c.label AS cl, list_sum([CAST(a[1] AS DOUBLE) * CAST(a[2] AS DOUBLE) FOR a IN list_zip(q.embedding, c.embedding)]) AS score FROM q, c{own}), r AS (SELECT *, row_number() OVER (PARTITION BY query ORDER BY round(score, 9) DESC, hit) AS rank FROM s)"


@query("WITH dummy AS (SELECT 1)" + _Q.format(own="") + " SELECT query, hit, CAST(rank AS INT) AS rank, round(score, 6) AS score FROM r WHERE rank <= 10")
def e_retrieval(spark, sf):
    e = table(spark, sf, "embeddings")
    return evaluate.retrieval(e.filter("vec_id % 50 = 0"), e, 10).select("query", "hit", "rank", _R("score").alias("score"))


@query("WITH dummy AS (SELECT 1)" + _Q.format(own=" WHERE q.vec_id <> c.vec_id") + " SELECT count(*) AS queries, round(avg(hit1), 6) AS recall_1, round(avg(hit10), 6) AS recall_10, round(avg(rr), 6) AS mrr FROM (SELECT query, max(CASE WHEN rank = 1 AND ql = cl THEN 1 ELSE 0 END) AS hit1, max(CASE WHEN ql = cl THEN 1 ELSE 0 END) AS hit10, coalesce(max(CASE WHEN ql = cl THEN 1 / rank END), 0) AS rr FROM r WHERE rank <= 10 GROUP BY query)")
def e_recall(spark, sf):
    """A query's own row would always be its first hit; it is none here."""
    e = table(spark, sf, "embeddings")
    m = evaluate.recall(evaluate.retrieval(e.filter("vec_id % 50 = 0"), e, 10, own=False))
    return m.select("queries", *(_R(k).alias(k) for k in ("recall_1", "recall_10", "mrr")))


_TOK = "SELECT conv_id, turn, role, unnest(string_split(lower(text), ' ')) AS w FROM conversations"


@query(f"WITH t AS ({_TOK}), k AS (SELECT conv_id, turn, w, count(*) AS n FROM t GROUP BY ALL), l AS (SELECT conv_id, turn, sum(n) AS len FROM k GROUP BY ALL), p AS (SELECT a.conv_id, a.turn FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1 WHERE a.role = 'user' AND b.role = 'assistant'), o AS (SELECT p.conv_id, p.turn, coalesce(sum(CASE WHEN y.n IS NULL THEN 0 ELSE least(x.n, y.n) END), 0) AS hit FROM p LEFT JOIN k x ON x.conv_id = p.conv_id AND x.turn = p.turn LEFT JOIN k y ON y.conv_id = p.conv_id AND y.turn = p.turn + 1 AND y.w = x.w GROUP BY ALL) SELECT o.conv_id, o.turn, round(hit / b.len, 6) AS precision, round(hit / a.len, 6) AS recall FROM o JOIN l a ON a.conv_id = o.conv_id AND a.turn = o.turn JOIN l b ON b.conv_id = o.conv_id AND b.turn = o.turn + 1")
def e_unigram(spark, sf):
    c = table(spark, sf, "conversations")
    nxt = c.filter("role = 'assistant'").select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("text").alias("candidate"))
    pairs = c.filter("role = 'user'").select("conv_id", "turn", F.col("text").alias("reference")).join(nxt, ["conv_id", "turn"])
    u = evaluate.unigram(pairs, ["conv_id", "turn"])
    return u.select("conv_id", "turn", _R("precision").alias("precision"), _R("recall").alias("recall"))


@query()
def e_rouge(spark, sf):
    c = table(spark, sf, "conversations")
    nxt = c.filter("role = 'assistant'").select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("text").alias("candidate"))
    pairs = c.filter("role = 'user'").select("conv_id", "turn", F.col("text").alias("reference")).join(nxt, ["conv_id", "turn"])
    return evaluate.rouge_l(pairs).select("conv_id", "turn", "rouge_l")


@query(with_views("cells", " SELECT scene_id, r, c, round(re, 4) + 0.0 AS re, round(im, 4) + 0.0 AS im FROM cells"))
def m10_subap_sum(spark, sf):
    """The sub-apertures of a scene, added up: the scene."""
    p = physics.subapertures(scene_cells(spark, sf), scenes(spark)).groupBy("scene_id", "r", "c").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))
    return p.filter(F.hypot("re", "im") > 1e-6).select("scene_id", "r", "c", _R("re", 4).alias("re"), _R("im", 4).alias("im"))
