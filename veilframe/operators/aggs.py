"""Aggregations used around a release."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def agg_basic(df: DataFrame, by: list[str], column: str) -> DataFrame:
    return df.groupBy(*by).agg(F.count(column).alias("n"), F.sum(column).alias("total"), F.avg(column).alias("mean"), F.min(column).alias("low"), F.max(column).alias("high"))


def agg_stats(df: DataFrame, by: list[str], x: str, y: str) -> DataFrame:
    """Deviations, covariances, correlation, and shape by central moments (population forms)."""
    m = df.groupBy(*by).agg(F.avg(x).alias("__m"), F.stddev_pop(x).alias("__s"))
    z = (F.col(x) - F.col("__m")) / F.col("__s")
    return df.join(F.broadcast(m), by).groupBy(*by).agg(F.var_samp(x).alias("var_samp"), F.var_pop(x).alias("var_pop"), F.stddev_samp(x).alias("sd_samp"), F.covar_samp(x, y).alias("covar_samp"), F.covar_pop(x, y).alias("covar_pop"), F.corr(x, y).alias("corr"), F.avg(z * z * z).alias("skewness"), (F.avg(z * z * z * z) - 3).alias("kurtosis"), F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"))


def agg_distinct(df: DataFrame, by: list[str], column: str, approximate: bool = False) -> DataFrame:
    return df.groupBy(*by).agg((F.approx_count_distinct(column, 0.02) if approximate else F.count_distinct(column)).alias("distinct"))


def agg_quantile(df: DataFrame, by: list[str], column: str, approximate: bool = False) -> DataFrame:
    """Quartiles; the approximate form merges sketches of bounded size."""
    q = [F.percentile_approx(column, p, 10_000) if approximate else F.percentile(column, p) for p in (0.25, 0.5, 0.75)]
    return df.groupBy(*by).agg(*(c.alias(n) for c, n in zip(q, ("q1", "median", "q3"), strict=True)))


def agg_mode(df: DataFrame, by: list[str], column: str) -> DataFrame:
    """The most frequent value, ties to the smallest: counts first, so no group's values meet in one buffer."""
    counts = df.groupBy(*by, column).agg(F.count(F.lit(1)).alias("c"))
    return counts.groupBy(*by).agg(F.min(F.struct((-F.col("c")).alias("n"), F.col(column).alias("v")))["v"].alias("mode"))


def agg_argmax(df: DataFrame, by: list[str], take: str, order: Column) -> DataFrame:
    return df.groupBy(*by).agg(F.max_by(take, order).alias("at_max"), F.min_by(take, order).alias("at_min"))


def agg_collect(df: DataFrame, by: list[str], column: str) -> DataFrame:
    """Sorted distinct values; for columns of few values."""
    return df.groupBy(*by).agg(F.sort_array(F.collect_set(column)).alias("items"))


def agg_filtered(df: DataFrame, by: list[str], column: str, condition: Column) -> DataFrame:
    return df.groupBy(*by).agg(F.sum(F.when(condition, F.col(column))).alias("inside"), F.sum(F.when(~condition, F.col(column))).alias("outside"))


def agg_sets(df: DataFrame, columns: list[str], value: str, kind: str = "cube") -> DataFrame:
    """Totals over rollup or cube levels, with the level's number."""
    grouped = df.rollup(*columns) if kind == "rollup" else df.cube(*columns)
    return grouped.agg(F.sum(value).alias("total"), F.grouping_id(*columns).cast("long").alias("level"))


def pivot_sum(df: DataFrame, by: str, column: str, values: list[str], value: str) -> DataFrame:
    return df.groupBy(by).pivot(column, values).agg(F.sum(value))


def to_long(df: DataFrame, keys: list[str], columns: list[str]) -> DataFrame:
    return df.unpivot(keys, columns, "attr", "v")


def class_moments(df: DataFrame, label: str, columns: list[str]) -> DataFrame:
    return df.groupBy(label).agg(F.count(F.lit(1)).alias("n"), *(F.avg(c).alias(f"m_{c}") for c in columns), *(F.var_samp(c).alias(f"v_{c}") for c in columns))
