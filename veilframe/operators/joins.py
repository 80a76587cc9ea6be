"""Joins around a release. Columns of the two sides have different names."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def _on(left: str, right: str) -> Column:
    return F.col(left) == F.col(right)


def join_broadcast(big: DataFrame, small: DataFrame, left: str, right: str, most_rows: int = 1_000_000) -> DataFrame:
    """Sends the small side to every task if its row count allows; else lets the planner choose."""
    return big.join(F.broadcast(small) if small.count() <= most_rows else small, _on(left, right))


def join_shuffle_hash(a: DataFrame, b: DataFrame, left: str, right: str) -> DataFrame:
    return a.join(b.hint("shuffle_hash"), _on(left, right))


def join_sort_merge(a: DataFrame, b: DataFrame, left: str, right: str) -> DataFrame:
    return a.join(b.hint("merge"), _on(left, right))


def join_outer(a: DataFrame, b: DataFrame, left: str, right: str, how: str = "left") -> DataFrame:
    return a.join(b, _on(left, right), how)


def join_semi(a: DataFrame, b: DataFrame, left: str, right: str) -> DataFrame:
    return a.join(b, _on(left, right), "left_semi")


def join_anti(a: DataFrame, b: DataFrame, left: str, right: str) -> DataFrame:
    return a.join(b, _on(left, right), "left_anti")


def join_null_safe(a: DataFrame, b: DataFrame, left: str, right: str) -> DataFrame:
    return a.join(b, F.col(left).eqNullSafe(F.col(right)))


def join_small_cross(a: DataFrame, b: DataFrame) -> DataFrame:
    """All pairs with a side of known small size (candidates, matrix cells)."""
    return a.join(F.broadcast(b))


def join_range(values: DataFrame, ranges: DataFrame, value: str, low: str, high: str, width: float) -> DataFrame:
    """low <= value < high, by slots of `width`: an equi join, then the exact condition."""
    slot = lambda c: F.floor(F.col(c) / width).cast("long")
    wide = ranges.withColumn("__slot", F.explode(F.sequence(slot(low), slot(high))))
    return values.withColumn("__at", slot(value)).join(wide, F.col("__at") == F.col("__slot")).where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("__at", "__slot")


def join_interval(a: DataFrame, b: DataFrame, ta: str, tb: str, seconds: int, on: Column) -> DataFrame:
    """Pairs at most so many seconds apart (epoch columns), by slots of that length."""
    wide = b.withColumn("__slot", F.explode(F.array(*(F.floor(F.col(tb) / seconds) + i for i in (-1, 0, 1)))))
    return a.withColumn("__at", F.floor(F.col(ta) / seconds)).join(wide, (F.col("__at") == F.col("__slot")) & on).where(F.abs(F.col(ta) - F.col(tb)) <= seconds).drop("__at", "__slot")


def join_asof(a: DataFrame, b: DataFrame, by: tuple[str, str], ts: tuple[str, str], take: list[str]) -> DataFrame:
    """For each row of a the latest row of b at or before it, by key: a union and one window, no range join."""
    left = a.withColumns({"__k": F.col(by[0]), "__t": F.col(ts[0]), "__side": F.lit(1)})
    right = b.select(F.col(by[1]).alias("__k"), F.col(ts[1]).alias("__t"), F.lit(0).alias("__side"), F.struct(*take).alias("__got"))
    w = Window.partitionBy("__k").orderBy("__t", "__side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = left.unionByName(right, allowMissingColumns=True).withColumn("__got", F.last("__got", ignorenulls=True).over(w))
    return both.where("__side = 1").select(*a.columns, *(F.col(f"__got.{c}").alias(c) for c in take))


def pair_rows(df: DataFrame, key: str, columns: list[str], sample: Column) -> DataFrame:
    """Pairs of sampled rows, each once; the sample's size is the caller's to bound."""
    rows = df.where(sample)
    x, y = rows.select(F.col(key).alias("k1"), *(F.col(c).alias(f"{c}_1") for c in columns)), rows.select(F.col(key).alias("k2"), *(F.col(c).alias(f"{c}_2") for c in columns))
    return x.join(y, F.col("k1") < F.col("k2"))


def search_rows(df: DataFrame, key: str, columns: list[str], every: int = 20) -> DataFrame:
    """Rows whose key is divisible by `every` (k1), each against all other rows (k2)."""
    x, y = (df.select(F.col(key).alias(f"k{i}"), *(F.col(c).alias(f"{c}_{i}") for c in columns)) for i in (1, 2))
    spread = y.repartition(4 * df.sparkSession.sparkContext.defaultParallelism, "k2")  # a short table is one task's otherwise
    return spread.join(x.where(F.col("k1") % every == 0), F.col("k1") != F.col("k2"))
