"""Projection, filters, nulls, samples and deduplication before a release."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.rng import key_text, uniform


def project(df: DataFrame, exprs: dict[str, Column | str]) -> DataFrame:
    return df.select(*((F.expr(e) if isinstance(e, str) else e).alias(name) for name, e in exprs.items()))


def to_double(df: DataFrame, columns: list[str]) -> DataFrame:
    """Casts, with null for what is no number."""
    return df.withColumns({c: F.col(c).try_cast("double") for c in columns})


def filter_rows(df: DataFrame, predicate: Column | str) -> DataFrame:
    return df.where(predicate)


def null_policy(df: DataFrame, columns: list[str], mode: str = "drop", value: float = 0.0) -> DataFrame:
    if mode == "drop":
        return df.dropna(subset=columns)
    if mode == "fill":
        return df.fillna(value, subset=columns)
    raise ValueError(f"mode is drop or fill, not {mode}")


def case_when(cases: list[tuple[Column, object]], otherwise: object = None) -> Column:
    out = F.lit(otherwise)
    for condition, value in reversed(cases):
        out = F.when(condition, value).otherwise(out)
    return out


def keyed_sample(df: DataFrame, keys: list[str], share: float, seed: str = "sample") -> DataFrame:
    """The same rows on every run, engine and partitioning."""
    return df.where(uniform(seed, "sample", key_text(keys)) < share)


def dedupe(df: DataFrame, keys: list[str], order: list[Column]) -> DataFrame:
    """The first row of every key by an order."""
    return df.withColumn("__k", F.row_number().over(Window.partitionBy(*keys).orderBy(*order))).where("__k = 1").drop("__k")
