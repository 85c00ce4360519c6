"""Counts that describe a corpus: by place, in the tail, on a grid, in roll-ups."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def top_n(df: DataFrame, key: str, n: int, distinct: str | None = None) -> DataFrame:
    """Counts of rows (or of distinct values) of the n largest keys, and of all others as `Other`; ties by key.

    The ranking window sees one row a key.
    """
    counted = df.groupBy(key).agg((F.count_distinct(distinct) if distinct else F.count("*")).alias("n"))
    first = counted.orderBy(F.desc("n"), key).limit(n).select(F.col(key).alias("_top"))
    named = counted.join(F.broadcast(first), counted[key] == F.col("_top"), "left")
    return named.groupBy(F.coalesce("_top", F.lit("Other")).alias(key)).agg(F.sum("n").alias("n"))


def coverage(df: DataFrame) -> DataFrame:
    """Samples, distinct cities and countries, and the share of the leading country."""
    by = df.groupBy("country").agg(F.count("*").alias("n"))
    total = df.agg(F.count("*").alias("samples"), F.count_distinct("city_id").alias("cities"), F.count_distinct("country").alias("countries"))
    return total.crossJoin(by.agg((F.max("n") / F.sum("n")).alias("leading_share")))


def tail(df: DataFrame, key: str, share: float = 0.8) -> DataFrame:
    """Number of keys, Gini coefficient of their counts, and how many of the largest hold the share."""
    counted = df.groupBy(key).agg(F.count("*").alias("n"))
    everything = Window.partitionBy(F.lit(1))
    ranked = counted.select(
        "n", F.row_number().over(everything.orderBy(F.desc("n"), key)).alias("rank"), F.sum("n").over(everything).alias("total"),
        F.sum("n").over(everything.orderBy(F.desc("n"), key).rowsBetween(Window.unboundedPreceding, 0)).alias("cum"), F.count("*").over(everything).alias("keys"),
    )
    gini = 1 - 2 * F.sum(F.col("n") * (F.col("rank") - 0.5)) / F.max("total") / F.max("keys")
    return ranked.agg(F.count("*").alias("keys"), gini.alias("gini"), F.min(F.when(F.col("cum") / F.col("total") >= share, F.col("rank"))).cast("long").alias("ranks_to_80"))


def density(df: DataFrame, degrees: int) -> DataFrame:
    """Scenes by cell of a grid over latitude and longitude."""
    cell = lambda c: (F.floor(F.col(c) / degrees) * degrees).cast("int")
    return df.groupBy(cell("lat0").alias("lat"), cell("lon0").alias("lon")).agg(F.count("*").alias("scenes"))


def rollup(df: DataFrame, keys: list[str]) -> DataFrame:
    return df.rollup(*keys).agg(F.count("*").alias("n"), F.grouping_id().alias("level"))


def cube(df: DataFrame, keys: list[str]) -> DataFrame:
    return df.cube(*keys).agg(F.count("*").alias("n"), F.grouping_id().alias("level"))
