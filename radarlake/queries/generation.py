"""The generation baseline on the given tables: augmentation, noise, masks, attention in SQL; the stand-in generator by invariants."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from radarlake.methods import caption, generate
from radarlake.methods.lexicon import PART_CATEGORIES
from radarlake.queries.captions import _BEST
from radarlake.registry import query
from radarlake.standins import captions, table, vec_patches, with_views

_R = lambda c, n=6: (F.round(c, n) + 0.0)
C = F.col
#: Cells of a patch, and classes.
WIDTH, CLASSES = 64, 10

_U = "((CAST('0x' || substr(md5({}), 1, 8) AS BIGINT) + 0.5e0) / 4294967296e0)"


@query(with_views("captions", f""", d AS (SELECT sample_id, list_element(['SHORT', 'MID', 'LONG'], CAST(least(2, floor({_U.format("sample_id || '-3'")} * 3)) AS INT) + 1) AS variant FROM (SELECT DISTINCT sample_id FROM captions)),
w AS (SELECT sample_id, variant, string_split(text, ' ') AS w FROM d JOIN captions USING (sample_id, variant))
SELECT sample_id, variant, 'radar: ' || array_to_string([w[i + 1] FOR i IN range(len(w)) IF {_U.format("sample_id || '-3-' || i")} >= 0.1e0], ' ') AS text FROM w"""))
def m11_augment(spark, sf):
    wide = captions(spark, sf).groupBy("sample_id").agg(F.map_from_entries(F.collect_list(F.struct("variant", "text"))).alias("captions"))
    return generate.augment(wide, 3, 0.1, prefix="radar: ").select("sample_id", "variant", "text")


@query(with_views("patches", f" SELECT patch_id, r, c, round(sqrt(0.6e0) * re + sqrt(0.4e0) * sqrt(-2 * ln({_U.format(chr(39).join(['patch_id || ', '-', ' || r || ', '-', ' || c || ', '-re-7-a', '']))})) * cos(2 * pi() * {_U.format(chr(39).join(['patch_id || ', '-', ' || r || ', '-', ' || c || ', '-re-7-b', '']))}), 5) + 0.0 AS re FROM patches"))
def m11_noise(spark, sf):
    n = generate.noise(vec_patches(spark, sf), 0.6, 7, ("re",), ("patch_id", "r", "c"))
    return n.select("patch_id", "r", "c", _R("re", 5).alias("re"))


@query(with_views("patches", ", k AS (SELECT unnest(['inpaint', 'outpaint', 'half']) AS kind), m AS (SELECT kind, patch_id, re * re + im * im AS e, CASE kind WHEN 'inpaint' THEN NOT (r BETWEEN 2 AND 5 AND c BETWEEN 2 AND 5) WHEN 'outpaint' THEN r BETWEEN 2 AND 5 AND c BETWEEN 2 AND 5 ELSE c < 4 END AS known FROM patches, k) SELECT kind, patch_id, count(*) FILTER (known) AS cells, round(sum(CASE WHEN known THEN e ELSE 0 END), 6) AS energy FROM m GROUP BY ALL"))
def m11_masks(spark, sf):
    """Cells that each mask gives of each patch, and their energy."""
    one = F.array(*(F.struct(F.lit(k).alias("kind"), generate.known(k, 8, C("r"), C("c")).alias("known")) for k in generate.MASKS))
    m = vec_patches(spark, sf).select("patch_id", (C("re") * C("re") + C("im") * C("im")).alias("e"), F.explode(one).alias("m"))
    return m.groupBy("m.kind", "patch_id").agg(F.count_if("m.known").alias("cells"), _R(F.sum(F.when(C("m.known"), C("e")).otherwise(0.0))).alias("energy"))


@query("""WITH q AS (SELECT label, list(m ORDER BY i) AS q FROM (SELECT label, i, avg(CAST(embedding[i] AS DOUBLE)) AS m FROM embeddings, range(1, 65) t(i) GROUP BY ALL) GROUP BY label),
s AS (SELECT q.label AS token, vec_id AS patch, list_sum([q.q[i] * CAST(embedding[i] AS DOUBLE) FOR i IN range(1, 65)]) / 8 AS s FROM q, embeddings),
e AS (SELECT token, patch, exp(s - max(s) OVER (PARTITION BY token)) AS e FROM s) SELECT token, patch, round(e / sum(e) OVER (PARTITION BY token), 8) AS weight FROM e""")
def m11_attention(spark, sf):
    """A token for each class, the mean of its vectors, over all patches."""
    e = table(spark, sf, "embeddings").select("vec_id", "label", C("embedding").cast("array<double>").alias("x"))
    means = e.select("label", F.posexplode("x").alias("p", "v")).groupBy("label", "p").agg(F.avg("v").alias("m"))
    tokens = means.groupBy(C("label").alias("token")).agg(F.transform(F.sort_array(F.collect_list(F.struct("p", "m"))), lambda s: s["m"]).alias("q"))
    a = generate.attention(tokens, e.select(C("vec_id").alias("patch"), C("x").alias("k")), "token", "patch")
    return a.select("token", "patch", _R("weight", 8).alias("weight"))


def _patches(spark, sf):
    return table(spark, sf, "embeddings").select(C("vec_id").alias("key"), "label", C("embedding").cast("array<double>").alias("x"))


def _model(spark, sf):
    return generate.fit_denoiser(_patches(spark, sf), WIDTH, CLASSES)


@query()
def m11_generate(spark, sf):
    """Ten patches of each class from noise."""
    wanted = spark.range(10 * CLASSES).select(C("id").alias("key"), (C("id") % CLASSES).cast("int").alias("label"))
    return generate.text_to_image(_model(spark, sf), wanted)


@query()
def m11_variant(spark, sf):
    """Variants of all patches towards the next class, at half strength."""
    p = _patches(spark, sf).withColumn("label", ((C("label") + 1) % CLASSES).cast("int"))
    return generate.variant(_model(spark, sf), p, 0.5)


def _middle() -> np.ndarray:
    r, c = np.divmod(np.arange(WIDTH), 8)
    return (r >= 2) & (r < 6) & (c >= 2) & (c < 6)


@query("SELECT vec_id AS key, CAST(48 AS INT) AS given, true AS unchanged FROM embeddings")
def m11_inpaint(spark, sf):
    """The middle of all patches made anew; the cells that are given stay as they are."""
    given = ~_middle()
    p = _patches(spark, sf)
    made = generate.inpaint(_model(spark, sf), p, given).select("key", C("x").alias("made"))
    places = F.array(*(F.lit(int(i)) for i in np.flatnonzero(given)))
    j = p.join(made, "key")
    same = F.forall(places, lambda i: F.abs(F.get(C("x"), i) - F.get(C("made"), i)) < 1e-12)
    return j.select("key", F.lit(int(given.sum())).alias("given"), same.alias("unchanged"))


@query("SELECT vec_id AS key, CAST(16 AS INT) AS given, true AS unchanged FROM embeddings")
def m11_outpaint(spark, sf):
    """The surroundings of the middle of all patches made anew."""
    given = _middle()
    p = _patches(spark, sf)
    made = generate.inpaint(_model(spark, sf), p, given).select("key", C("x").alias("made"))
    places = F.array(*(F.lit(int(i)) for i in np.flatnonzero(given)))
    same = F.forall(places, lambda i: F.abs(F.get(C("x"), i) - F.get(C("made"), i)) < 1e-12)
    return p.join(made, "key").select("key", F.lit(int(given.sum())).alias("given"), same.alias("unchanged"))


@query()
def m11_adapter(spark, sf):
    """Error of the frozen base and of adapters of rising rank, fitted to the patches of odd keys; rank 0 is the base alone."""
    p = _patches(spark, sf)
    base = generate.fit_denoiser(p.filter("key % 2 = 0"), WIDTH, CLASSES)
    rows = []
    for rank in (0, 1, 4, 16, 64):
        model, errors = generate.fit_adapter(base, p.filter("key % 2 = 1"), rank)
        rows.append((rank, *model.parameters(), float(sum(errors))))
    return spark.createDataFrame(rows, "rank int, base_parameters long, adapter_parameters long, error double")


@query()
def m11_quality(spark, sf):
    """How far generated patches are from real ones by class: the generator, the base at no strength (the real patches), the nearest real patch."""
    real, model = _patches(spark, sf), _model(spark, sf)
    wanted = real.select("key", "label")
    out = None
    for name, made in (("generated", generate.text_to_image(model, wanted)), ("itself", generate.variant(model, real, 0.0)), ("nearest", generate.nearest_real(wanted, real))):
        q = generate.quality(made, real).withColumn("maker", F.lit(name))
        out = q if out is None else out.unionByName(q)
    return out


@query(_BEST + """, n AS (SELECT p_brand AS place, category, count(*) AS n FROM l JOIN part ON p_partkey = sample_id GROUP BY ALL), t AS (SELECT *, row_number() OVER (PARTITION BY place ORDER BY n DESC, category) AS r FROM n)
SELECT place, 'count' AS kind, CAST(json_object('question', 'How many ' || category || ' samples are there in ' || place || '?', 'answer', CAST(n AS VARCHAR)) AS VARCHAR) AS record FROM n UNION ALL SELECT place, 'most', CAST(json_object('question', 'Which category is the most common in ' || place || '?', 'answer', category) AS VARCHAR) FROM t WHERE r = 1""")
def m12_questions(spark, sf):
    p = table(spark, sf, "part").select(C("p_name").alias("text"), C("p_brand").alias("brand"))
    return generate.qa_records(caption.label(p, PART_CATEGORIES), "category", "brand")
