"""Captions: generation behind an interface, cleaning rules, keyword labels, text statistics.

Models are plug-ins; what ships are deterministic stand-ins that are named as such.
"""

from __future__ import annotations

import re
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from radarlake.methods.lexicon import CATEGORIES, COLORS, HEDGES

VARIANTS = ("SHORT", "MID", "LONG")
Vocabulary = dict[str, tuple[tuple[str, ...], tuple[str, ...]]]


#: The signs that white space is made of.
SPACES = " \t\n\x0b\f\r"


def tokens(text: Column, most: int | None = None) -> Column:
    """Words between white space; with `most`, what follows that many words is one last value."""
    return F.split(F.btrim(text, F.lit(SPACES)), r"\s+", -1 if most is None else most + 1)


def first_words(text: Column, n: Column, most: int | None = None) -> Column:
    """Stand-in captioner: the first n words, n at most `most`, so that the rest of the text is not split."""
    return F.array_join(F.slice(tokens(text, most), F.lit(1), n.cast("int")), " ")


def generate(df: DataFrame, model: Callable[[Column, str], Column], variants: tuple[str, ...] = VARIANTS, text: str = "text") -> DataFrame:
    """A map of captions by variant; `model` gives a Column, or use `generate_with` for a batch model."""
    pairs = [x for v in variants for x in (F.lit(v), model(F.col(text), v))]
    return df.withColumn("captions", F.create_map(*pairs))


def requests(df: DataFrame, prompts: dict[str, str], text: str = "text") -> DataFrame:
    """A row for each text and length of caption: the instruction, and what a captioner is sent, the instruction and the text."""
    each = F.array(*(F.struct(F.lit(v).alias("variant"), F.lit(p).alias("prompt")) for v, p in prompts.items()))
    return df.withColumn("of", F.explode(each)).select("*", "of.variant", "of.prompt", F.concat("of.prompt", F.lit("\n"), F.coalesce(text, F.lit(""))).alias("request")).drop("of")


def generate_with(df: DataFrame, model: Callable[[list[str]], list[str]], text: str = "text", into: str = "caption") -> DataFrame:
    """Runs a batch model over Arrow batches; the model is loaded once a worker by its own caching."""

    def run(batches):
        for b in batches:
            made = model([x or "" for x in b.column(b.schema.get_field_index(text)).to_pylist()])
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(made, pa.string())], names=[*b.schema.names, into])

    schema = ", ".join(f"`{c}` {t}" for c, t in df.dtypes)
    return df.mapInArrow(run, f"{schema}, `{into}` string")


def long(df: DataFrame) -> DataFrame:
    """Rows (sample_id, variant, text)."""
    return df.select("sample_id", F.explode("captions").alias("variant", "text"))


def _any(words: tuple[str, ...]) -> str:
    return "|".join(re.escape(w) for w in sorted(words, key=lambda w: (-len(w), w)))


def strip_colors(text: Column, colors: tuple[str, ...] = COLORS) -> Column:
    """Drops color words with what joins them to a further color, in one pattern."""
    c = _any(colors)
    return F.trim(F.regexp_replace(F.regexp_replace(text, rf"(?i)\b(?:{c})\b(?:(?:\s*,\s*|\s+and\s+|\s+or\s+)(?:{c})\b)*", ""), r"\s+", " "))


def strip_hedges(text: Column, hedges: tuple[str, ...] = HEDGES) -> Column:
    return F.trim(F.regexp_replace(F.regexp_replace(text, rf"(?i)\b(?:{_any(hedges)})\b", ""), r"\s+", " "))


def residual_rates(df: DataFrame, by: list[str], text: str = "text") -> DataFrame:
    """Share of texts that still hold a color word or a hedge."""
    has = lambda words: F.avg(F.col(text).rlike(rf"(?i)\b(?:{_any(words)})\b").cast("int"))
    return df.groupBy(*by).agg(F.count("*").alias("n"), has(COLORS).alias("colors"), has(HEDGES).alias("hedges"))


def normalize(text: Column) -> Column:
    """White space, spaces before punctuation, a capital first letter, one full stop at the end; twice is once."""
    one = F.trim(F.regexp_replace(text, r"\s+", " "))
    tight = F.regexp_replace(F.regexp_replace(one, r"\s+([,.;:])", "$1"), r"([,;:])(?=[,;:.])", "")
    bare = F.regexp_replace(tight, r"[\s,;:.]+$", "")
    return F.when(bare == "", "").otherwise(F.concat(F.upper(F.substring(bare, 1, 1)), F.substr(bare, F.lit(2)), F.lit(".")))


def clean(text: Column) -> Column:
    """All rules in their order."""
    return normalize(strip_hedges(strip_colors(text)))


def clean_with(df: DataFrame, model: Callable[[list[str]], list[str]], text: str = "text") -> DataFrame:
    """The rules, then a model that rewrites batches of texts; what it returns is held to the rules once more. Nulls stay null."""
    ruled = df.withColumn(text, clean(F.col(text)))
    made = generate_with(ruled, model, text, "_made")
    return made.withColumn(text, F.when(F.col(text).isNotNull(), clean(F.col("_made")))).drop("_made")


def _hits(text: Column, words: tuple[str, ...]) -> Column:
    return F.regexp_count(F.lower(text), F.lit(rf"\b(?:{_any(words)})s?\b")) if words else F.lit(0)


def scores(text: Column, vocabulary: Vocabulary = CATEGORIES) -> Column:
    """(hits, priority, category) of each category, best first; a word that rules a category out sets it to none."""
    one = [F.struct(F.when(_hits(text, no) > 0, 0).otherwise(_hits(text, yes)).cast("int").alias("hits"), F.lit(-k).alias("priority"), F.lit(name).alias("category")) for k, (name, (yes, no)) in enumerate(vocabulary.items())]
    return F.sort_array(F.array(*one), asc=False)


def label(df: DataFrame, vocabulary: Vocabulary = CATEGORIES, text: str = "text") -> DataFrame:
    """`category` with the most hits, ties by the vocabulary's order, `other` without a hit."""
    best = df.withColumn("_best", scores(F.col(text), vocabulary)[0])
    return best.withColumn("hits", F.col("_best.hits")).withColumn("category", F.when(F.col("hits") > 0, F.col("_best.category")).otherwise("other")).drop("_best")


def label_multi(df: DataFrame, vocabulary: Vocabulary = CATEGORIES, text: str = "text") -> DataFrame:
    """A row per category with a hit."""
    hit = F.filter(scores(F.col(text), vocabulary), lambda s: s["hits"] > 0)
    return df.withColumn("_s", F.explode(hit)).withColumn("category", F.col("_s.category")).withColumn("hits", F.col("_s.hits")).drop("_s")


def distribution(labelled: DataFrame) -> DataFrame:
    """Counts and shares of categories."""
    n = labelled.groupBy("category").agg(F.count("*").alias("n"))
    return n.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy(F.lit(1))))


def stats(df: DataFrame) -> DataFrame:
    """Captions and mean words by variant."""
    return df.groupBy("variant").agg(F.count("*").alias("n"), F.avg(F.size(tokens(F.col("text")))).alias("mean_words"))


def percentiles(df: DataFrame, exact: bool = True) -> DataFrame:
    """P10 and P90 of words: interpolated and discrete, or approximate."""
    w = df.select("variant", F.size(tokens(F.col("text"))).alias("w")).groupBy("variant")
    if not exact:
        return w.agg(F.percentile_approx("w", F.lit(0.1), F.lit(10000)).alias("p10"), F.percentile_approx("w", F.lit(0.9), F.lit(10000)).alias("p90"))
    disc = lambda p: F.expr(f"percentile_disc({p}) within group (order by w)")
    return w.agg(F.percentile("w", F.lit(0.1)).alias("p10"), F.percentile("w", F.lit(0.9)).alias("p90"), disc(0.1).alias("p10_disc"), disc(0.9).alias("p90_disc"))


def words(df: DataFrame) -> DataFrame:
    """Lower-cased letter-only tokens, one a row."""
    t = df.select("variant", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}+"), F.lit(0))).alias("word"))
    return t


def vocabulary(df: DataFrame, approx: bool = False) -> DataFrame:
    """Distinct words by variant: exact by a two-level distinct, or a mergeable sketch."""
    w = words(df)
    if approx:
        return w.groupBy("variant").agg(F.approx_count_distinct("word", 0.02).alias("vocabulary"))
    return w.distinct().groupBy("variant").agg(F.count("*").alias("vocabulary"))


def duplicates(df: DataFrame) -> DataFrame:
    """Share of captions beyond the first of their text, and share of captions whose text repeats."""
    n = df.groupBy("variant", F.md5("text").alias("h")).agg(F.count("*").alias("k"))
    total = F.sum("k")
    return n.groupBy("variant").agg(total.alias("n"), (1 - F.count("*") / total).alias("dup_extra"), (F.sum(F.when(F.col("k") > 1, F.col("k")).otherwise(0)) / total).alias("dup_member"))


def diversity(df: DataFrame) -> DataFrame:
    """Distinct words, running words and their ratio."""
    c = words(df).groupBy("variant", "word").agg(F.count("*").alias("k"))
    return c.groupBy("variant").agg(F.count("*").alias("types"), F.sum("k").alias("tokens"), (F.count("*") / F.sum("k")).alias("ratio"))


def top_words(df: DataFrame, n: int) -> DataFrame:
    """The n most frequent words of each variant, ties by the word."""
    c = words(df).groupBy("variant", "word").agg(F.count("*").alias("k"))
    rank = F.row_number().over(Window.partitionBy("variant").orderBy(F.desc("k"), "word"))
    return c.withColumn("rank", rank).filter(F.col("rank") <= n)
