"""Orders, top rows and set operations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def sort_total(df: DataFrame, column: str) -> DataFrame:
    return df.orderBy(F.col(column).asc_nulls_last())


def sort_local(df: DataFrame, *columns: str) -> DataFrame:
    return df.sortWithinPartitions(*columns)


def top_k(df: DataFrame, k: int, *order: Column) -> DataFrame:
    return df.orderBy(*order).limit(k)


def top_k_per_group(df: DataFrame, by: list[str], k: int, *order: Column) -> DataFrame:
    return df.withColumn("place", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("place") <= k)


def page(df: DataFrame, n: int, skip: int, *order: Column) -> DataFrame:
    return df.orderBy(*order).offset(skip).limit(n)


def set_union(a: DataFrame, b: DataFrame, distinct: bool = False) -> DataFrame:
    out = a.unionByName(b)
    return out.distinct() if distinct else out


def set_intersect(a: DataFrame, b: DataFrame, all_: bool = False) -> DataFrame:
    return a.intersectAll(b) if all_ else a.intersect(b)


def set_except(a: DataFrame, b: DataFrame, all_: bool = False) -> DataFrame:
    return a.exceptAll(b) if all_ else a.subtract(b)
