"""Window operators; every window has a partition key, so none gathers a whole table."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def win_rank(df: DataFrame, by: list[str], order: list[Column]) -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*order)
    return df.withColumns({"row_number": F.row_number().over(w), "rank": F.rank().over(w), "dense_rank": F.dense_rank().over(w), "percent_rank": F.percent_rank().over(w), "cume_dist": F.cume_dist().over(w), "ntile": F.ntile(4).over(w)})


def win_avg_rank(df: DataFrame, by: list[str], value: str) -> DataFrame:
    """Ranks with ties at the mean of their places."""
    w = Window.partitionBy(*by).orderBy(value)
    return df.withColumn("avg_rank", F.rank().over(w) + (F.count(F.lit(1)).over(Window.partitionBy(*by, value)) - 1) / 2.0)


def win_shift(df: DataFrame, by: list[str], order: list[Column], value: str) -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*order)
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return df.withColumns({"previous": F.lag(value).over(w), "next": F.lead(value).over(w), "first": F.first(value).over(whole), "last": F.last(value).over(whole), "second": F.nth_value(value, 2).over(whole)})


def win_running(df: DataFrame, by: list[str], order: list[Column], value: str) -> DataFrame:
    return df.withColumn("running", F.sum(value).over(Window.partitionBy(*by).orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow)))


def win_moving(df: DataFrame, by: list[str], order: list[Column], value: str, back: int = 5) -> DataFrame:
    return df.withColumn("moving", F.avg(value).over(Window.partitionBy(*by).orderBy(*order).rowsBetween(-back, -1)))


def win_range(df: DataFrame, by: list[str], seconds: Column, value: str, back: int) -> DataFrame:
    return df.withColumn("recent", F.sum(value).over(Window.partitionBy(*by).orderBy(seconds).rangeBetween(-back, 0)))


def win_share(df: DataFrame, by: list[str], value: str) -> DataFrame:
    return df.withColumn("share", F.col(value) / F.sum(value).over(Window.partitionBy(*by)))
