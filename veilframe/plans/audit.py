"""Auditors of privacy models that the method is set against: they measure a table and change nothing."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def k_anonymity(df: DataFrame, quasi: list[str]) -> DataFrame:
    """k (the smallest class), classes."""
    return df.groupBy(*quasi).agg(F.count(F.lit(1)).alias("c")).agg(F.min("c").alias("k"), F.count(F.lit(1)).alias("classes"))


def l_diversity(df: DataFrame, quasi: list[str], sensitive: str) -> DataFrame:
    """l: the least number of sensitive values in a class."""
    return df.groupBy(*quasi).agg(F.count_distinct(sensitive).alias("c")).agg(F.min("c").alias("l"))


def alpha_k(df: DataFrame, quasi: list[str], sensitive: str) -> DataFrame:
    """alpha (the largest share of one sensitive value in a class) and k."""
    cells = df.groupBy(*quasi, sensitive).agg(F.count(F.lit(1)).alias("c"))
    classes = cells.groupBy(*quasi).agg(F.sum("c").alias("n"), F.max("c").alias("top"))
    return classes.agg(F.max(F.col("top") / F.col("n")).alias("alpha"), F.min("n").alias("k"))


def t_closeness(df: DataFrame, quasi: list[str], sensitive: str) -> DataFrame:
    """t: the largest total variation distance between a class's sensitive values and all."""
    whole = df.groupBy(F.col(sensitive).alias("__s")).agg(F.count(F.lit(1)).alias("c")).withColumn("p", F.col("c") / df.groupBy().count().first()[0]).select("__s", "p")
    cells = df.groupBy(*quasi, F.col(sensitive).alias("__s")).agg(F.count(F.lit(1)).alias("c"))
    sizes = cells.groupBy(*quasi).agg(F.sum("c").alias("n"))
    seen = cells.join(sizes, quasi).join(F.broadcast(whole), "__s").select(*quasi, (F.col("c") / F.col("n")).alias("q"), "p")
    # values that a class lacks count with their whole share
    return seen.groupBy(*quasi).agg(F.sum(F.abs(F.col("q") - F.col("p"))).alias("d"), F.sum("p").alias("held")).agg(F.max((F.col("d") + 1 - F.col("held")) / 2).alias("t"))
