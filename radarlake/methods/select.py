"""Choice of scenes and what the choice rejects."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def rules(pols: tuple[str, ...] = ("VV", "HH"), incidence: tuple[float, float] = (10, 70), spacing: tuple[float, float] = (0.2, 2.0)) -> dict[str, Column]:
    """Named conditions that a scene must meet."""
    return {
        "pol": F.col("pol").isin(*pols),
        "incidence": F.col("incidence_deg").between(*incidence),
        "spacing_az": F.col("native_az_m").between(*spacing),
        "spacing_rg": F.col("native_rg_m").between(*spacing),
    }


def scenes(df: DataFrame, **limits) -> DataFrame:
    """Scenes that meet all rules; rows with a null in a rule's column go."""
    for condition in rules(**limits).values():
        df = df.filter(condition)
    return df


def audit(df: DataFrame, **limits) -> DataFrame:
    """How many scenes fail each rule, how many fail some, how many stay."""
    checks = {k: F.coalesce(c, F.lit(False)) for k, c in rules(**limits).items()}
    everything = F.lit(True)
    for c in checks.values():
        everything = everything & c
    failed = [F.count_if(~c).alias(f"fail_{k}") for k, c in checks.items()]
    return df.agg(F.count("*").alias("scenes"), *failed, F.count_if(everything).alias("kept"))


def by_environment(df: DataFrame, environment: Column, values: list[str], key: str = "continent") -> DataFrame:
    """Counts by key and environment, a column per environment."""
    return df.withColumn("environment", environment).groupBy(key).pivot("environment", values).count().na.fill(0, values)


def temporal(df: DataFrame, place: str, date: str, key: str, max_gap_days: int) -> DataFrame:
    """Stacks of one place: its passes by date, numbered anew after a gap of more than so many days; with the days since the pass before."""
    from pyspark.sql import Window

    order = Window.partitionBy(place).orderBy(date, key)
    gap = F.datediff(F.col(date), F.lag(date).over(order))
    opened = df.withColumn("gap", gap).withColumn("_new", (F.col("gap").isNull() | (F.col("gap") > max_gap_days)).cast("int"))
    stacked = opened.withColumn("stack", F.sum("_new").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    return stacked.withColumn("layer", F.row_number().over(Window.partitionBy(place, "stack").orderBy(date, key))).drop("_new")
