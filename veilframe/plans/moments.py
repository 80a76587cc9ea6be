"""Means, standard deviations and the covariance of the standardized table, in one pass over the records.

The covariance of standardized attributes is the correlation of the attributes, so no standardized copy is
made. Few attributes are aggregated declaratively; many by Arrow batches that add up shifted cross products,
whose sums over partitions are a grouped aggregation of n * n numbers.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

FEW = 8


@dataclass(frozen=True)
class Moments:
    attrs: tuple[str, ...]
    rows: int
    mean: np.ndarray
    sd: np.ndarray
    cov: np.ndarray  # of the standardized attributes

    @property
    def constant(self) -> list[str]:
        return [a for a, s in zip(self.attrs, self.sd, strict=True) if not s > 0]


def mean_std(df: DataFrame, attrs: list[str], ddof: int = 1) -> DataFrame:
    """Long form: attr, mean, sd."""
    sd = F.stddev_samp if ddof else F.stddev_pop
    row = df.agg(*(F.avg(a).alias(f"m{i}") for i, a in enumerate(attrs)), *(sd(a).alias(f"s{i}") for i, a in enumerate(attrs)))
    parts = F.array(*(F.struct(F.lit(a).alias("attr"), F.col(f"m{i}").alias("mean"), F.col(f"s{i}").alias("sd")) for i, a in enumerate(attrs)))
    return row.select(F.inline(parts))


def correlation(x: str, y: str) -> Column:
    """Null, not an error, where a side is constant."""
    return F.try_divide(F.covar_samp(x, y), F.stddev_samp(x) * F.stddev_samp(y))


def covariance_long(df: DataFrame, attrs: list[str]) -> DataFrame:
    """Long form i, j, cov (1-based) of the standardized attributes, for few attributes."""
    pairs = list(itertools.combinations_with_replacement(range(len(attrs)), 2))
    row = df.agg(*(correlation(attrs[i], attrs[j]).alias(f"c{i}_{j}") for i, j in pairs if i != j), F.count(F.lit(1)).alias("n"))
    cell = lambda i, j: F.lit(1.0) if i == j else F.col(f"c{min(i, j)}_{max(i, j)}")
    parts = [F.struct(F.lit(i + 1).alias("i"), F.lit(j + 1).alias("j"), cell(i, j).alias("cov")) for i in range(len(attrs)) for j in range(len(attrs))]
    return row.select(F.inline(F.array(*parts)))


def _gram(df: DataFrame, attrs: list[str], pilot: np.ndarray) -> tuple[int, np.ndarray, np.ndarray]:
    """Count, sums and cross products of the attributes less the pilot, added up over partitions."""
    n = len(attrs)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count, sums, cross = 0, np.zeros(n), np.zeros((n, n))
        for batch in batches:
            x = np.column_stack([batch.column(i).to_numpy(zero_copy_only=False) for i in range(n)]) - pilot
            count, sums, cross = count + len(x), sums + x.sum(axis=0), cross + x.T @ x
        if count:
            flat = np.concatenate([[count], sums, cross.ravel()])
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat)), pa.int32()), pa.array(flat)], names=["at", "v"])

    rows = df.select(*attrs).mapInArrow(work, "at int, v double").groupBy("at").agg(F.sum("v").alias("v")).collect()
    flat = np.zeros(1 + n + n * n)
    for r in rows:
        flat[r["at"]] = r["v"]
    return int(flat[0]), flat[1 : n + 1], flat[n + 1 :].reshape(n, n)


def fit(df: DataFrame, attrs: list[str] | tuple[str, ...], ddof: int = 1, method: str = "auto") -> Moments:
    """Moments of the attributes (doubles). method: "pairs", "gram", or "auto" by their number."""
    attrs, n = list(attrs), len(attrs)
    if method == "pairs" or method == "auto" and n <= FEW:
        pairs = list(itertools.combinations(range(n), 2))
        sd = F.stddev_samp if ddof else F.stddev_pop
        row = df.agg(F.count(F.lit(1)).alias("rows"), *(f(F.col(a)).alias(f"{k}{i}") for i, a in enumerate(attrs) for k, f in (("m", F.avg), ("s", sd))), *(correlation(attrs[i], attrs[j]).alias(f"c{i}_{j}") for i, j in pairs)).first()
        number = lambda x: float("nan") if x is None else float(x)
        cov = np.eye(n)
        for i, j in pairs:
            cov[i, j] = cov[j, i] = number(row[f"c{i}_{j}"])
        return Moments(tuple(attrs), row["rows"], np.array([number(row[f"m{i}"]) for i in range(n)]), np.nan_to_num(np.array([number(row[f"s{i}"]) for i in range(n)])), cov)
    first = df.select(*attrs).limit(1000).agg(*(F.avg(a) for a in attrs)).first()
    pilot = np.array([x or 0.0 for x in first])
    count, sums, cross = _gram(df, attrs, pilot)
    if count < 2:
        return Moments(tuple(attrs), count, pilot + (sums / max(count, 1)), np.zeros(n), np.full((n, n), np.nan))
    centred = cross - np.outer(sums, sums) / count
    sd = np.sqrt(np.maximum(np.diag(centred), 0) / (count - ddof))
    with np.errstate(invalid="ignore", divide="ignore"):
        cov = centred / (count - ddof) / np.outer(sd, sd)
    return Moments(tuple(attrs), count, pilot + sums / count, sd, cov)


def standardize(df: DataFrame, moments: Moments) -> DataFrame:
    """Each attribute less its mean, over its standard deviation."""
    return df.withColumns({a: (F.col(a) - float(m)) / float(s) for a, m, s in zip(moments.attrs, moments.mean, moments.sd, strict=True)})
