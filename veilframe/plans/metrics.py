"""Measures: guarantees, resistance, rank tests, Kolmogorov-Smirnov tests, entropy, biases."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .counted import entropies, greatest_gaps
from .held import hold
from .matrix import KEY
from .moments import Moments


def paired(orig: DataFrame, other: DataFrame, attrs: list[str], by: str = KEY) -> DataFrame:
    """Rows of two tables side by side by a key: x_<attr> and y_<attr>. Keys must not repeat (see as_matrix)."""
    x = orig.select(by, *(F.col(a).alias(f"x_{a}") for a in attrs))
    y = other.select(F.col(by).alias("__by"), *(F.col(a).alias(f"y_{a}") for a in attrs))
    return x.join(y, F.col(by) == F.col("__by")).drop("__by")


def diff_variance(pairs: DataFrame, attrs: list[str]) -> DataFrame:
    """attr, variance of y - x."""
    row = pairs.agg(*(F.var_samp(F.col(f"y_{a}") - F.col(f"x_{a}")).alias(f"v{i}") for i, a in enumerate(attrs)))
    return row.select(F.inline(F.array(*(F.struct(F.lit(a).alias("attr"), F.col(f"v{i}").alias("variance")) for i, a in enumerate(attrs)))))


def phi(pairs: DataFrame, attrs: list[str]) -> DataFrame:
    """The least of these variances."""
    return diff_variance(pairs, attrs).agg(F.min("variance").alias("phi"))


def resistance(pairs: DataFrame, attrs: list[str], scale: str = "both", sides: tuple[Moments, Moments] | None = None) -> DataFrame:
    """std_min and std_avg of the difference between original and reconstruction, standardized.

    scale "both": each side by its own moments; "orig": both by the original's. sides: the moments of x and of y where
    they are known; the pairs are then read once."""
    if sides:
        of = lambda k, i: ((m := sides[k == "y" and scale == "both"]).mean[i], m.sd[i])
        given = lambda k, i, a: (F.col(f"{k}_{a}") - float(of(k, i)[0])) / float(of(k, i)[1])
        return _least_and_mean(pairs.agg(*(F.stddev_samp(given("y", i, a) - given("x", i, a)).alias(f"d{i}") for i, a in enumerate(attrs))), len(attrs))
    pairs = hold(pairs)
    sd = {f"{k}_{a}": f(f"{k}_{a}").alias(f"{t}_{k}_{a}") for a in attrs for k in "xy" for t, f in (("sd", F.stddev_samp),)}
    mo = pairs.agg(*sd.values(), *(F.avg(f"{k}_{a}").alias(f"m_{k}_{a}") for a in attrs for k in "xy"))
    joined = pairs.join(F.broadcast(mo))

    def z(k: str, a: str) -> Column:
        by = k if scale == "both" else "x"
        return (F.col(f"{k}_{a}") - F.col(f"m_{by}_{a}")) / F.col(f"sd_{by}_{a}")

    return _least_and_mean(joined.agg(*(F.stddev_samp(z("y", a) - z("x", a)).alias(f"d{i}") for i, a in enumerate(attrs))), len(attrs))


def _least_and_mean(row: DataFrame, n: int) -> DataFrame:
    stds = F.array(*(F.col(f"d{i}") for i in range(n)))
    return row.select(F.array_min(stds).alias("std_min"), (F.aggregate(stds, F.lit(0.0), lambda s, x: s + x) / n).alias("std_avg"))


def average_rank(by: list[str], value: str, ascending: bool = True) -> Column:
    """Rank within a block, ties sharing the mean of their places."""
    w = Window.partitionBy(*by)
    order = w.orderBy(F.col(value).asc() if ascending else F.col(value).desc())
    return F.rank().over(order) + (F.count(F.lit(1)).over(Window.partitionBy(*by, value)) - 1) / 2.0


def friedman(df: DataFrame, block: list[str], treatment: str, value: str) -> DataFrame:
    """treatment, mean_rank, chi2, dof, p. Tie-corrected; p for two degrees of freedom, else see chi2_tail."""
    ranked = df.withColumns({"__r": average_rank(block, value), "__t": F.count(F.lit(1)).over(Window.partitionBy(*block, value))})
    whole = ranked.agg(F.sum((F.col("__t") * F.col("__t") - 1).cast("double")).alias("ties"), F.countDistinct(*block).alias("b"), F.countDistinct(treatment).alias("k"))
    means = ranked.groupBy(treatment).agg(F.avg("__r").alias("mean_rank"), F.sum("__r").alias("s"))
    b, k = F.col("b"), F.col("k")
    squares = means.agg(F.sum(F.col("s") * F.col("s")).alias("q"))
    plain = 12.0 * F.col("q") / (b * k * (k + 1)) - 3.0 * b * (k + 1)
    chi2 = plain / (1 - F.col("ties") / (b * k * (k * k - 1)))
    total = squares.join(whole).select(chi2.alias("chi2"), (k - 1).cast("int").alias("dof"))
    return means.join(F.broadcast(total)).select(F.col(treatment).alias("treatment"), "mean_rank", "chi2", "dof", F.when(F.col("dof") == 2, F.exp(-F.col("chi2") / 2)).alias("p"))


def chi2_tail(chi2: float, dof: int) -> float:
    """Upper tail of chi-square, by the series of the regularized incomplete gamma function."""
    a, x = dof / 2, chi2 / 2
    if x <= 0:
        return 1.0
    term = total = 1 / a
    k = a
    while abs(term) > 1e-16 * abs(total):
        k += 1
        term *= x / k
        total += term
    return max(0.0, 1 - total * math.exp(-x + a * math.log(x) - math.lgamma(a)))


def box_stats(df: DataFrame, by: list[str], value: str) -> DataFrame:
    """Quartiles, whiskers (farthest within 1.5 spreads) and the number of outliers."""
    q = df.groupBy(*by).agg(F.percentile(value, F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75))).alias("q"))
    rows = df.join(F.broadcast(q), by)
    low, high = F.col("q")[0] - 1.5 * (F.col("q")[2] - F.col("q")[0]), F.col("q")[2] + 1.5 * (F.col("q")[2] - F.col("q")[0])
    inside = (F.col(value) >= low) & (F.col(value) <= high)
    return rows.groupBy(*by).agg(F.max("q").alias("q"), F.min(F.when(inside, F.col(value))).alias("whisker_low"), F.max(F.when(inside, F.col(value))).alias("whisker_high"), F.sum((~inside).cast("long")).alias("outliers")).select(*by, F.col("q")[0].alias("q1"), F.col("q")[1].alias("median"), F.col("q")[2].alias("q3"), "whisker_low", "whisker_high", "outliers")


def ks_tail(d: float, n: int, m: int) -> float:
    """Asymptotic two-sample p value with the small-sample argument."""
    root = math.sqrt(n * m / (n + m))
    lam = (root + 0.12 + 0.11 / root) * d
    if lam < 0.2:
        return 1.0
    return min(1.0, max(0.0, 2 * sum((-1) ** (k - 1) * math.exp(-2 * k * k * lam * lam) for k in range(1, 101))))


def ks_cutoff(n: int, alpha: float = 0.05) -> int:
    """The least k for which two samples of n with statistic k / n are told apart."""
    return next((k for k in range(1, n + 1) if ks_tail(k / n, n, n) < alpha), n + 1)


def ks_tuples(pairs: DataFrame, moments: Moments, alpha: float = 0.05, by: str = KEY, other: Moments | None = None) -> DataFrame:
    """key, d, rejected: for each record, its standardized values against the other's, as two samples of n."""
    attrs, n = moments.attrs, len(moments.attrs)
    right, cutoff = other or moments, ks_cutoff(len(moments.attrs), alpha)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = lambda at, m: [(batch.column(at + i).to_numpy(zero_copy_only=False) - m.mean[i]) / m.sd[i] for i in range(n)]
            x, y = values(1, moments), values(1 + n, right)
            k = np.zeros(batch.num_rows, dtype=np.int16)
            for v in (*x, *y):
                gap = np.zeros(batch.num_rows, dtype=np.int16)
                for i in range(n):
                    gap += x[i] <= v
                    gap -= y[i] <= v
                np.maximum(k, np.abs(gap), out=k)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(k / float(n)), pa.array(k >= cutoff)], names=["key", "d", "rejected"])

    rows = pairs.select(F.col(by).alias("key"), *(F.col(f"{k}_{a}").cast("double") for k in "xy" for a in attrs))
    return rows.mapInArrow(work, f"key {rows.schema['key'].dataType.simpleString()}, d double, rejected boolean")


def ks_attributes(orig: DataFrame, other: DataFrame, attrs: list[str]) -> DataFrame:
    """attr, d, n, m: the two-sample statistic of every attribute. Nulls are left out.

    Values are counted first; the running sums are two-level (by slots that hold like numbers of values whatever
    their spread, then inside a slot), so no task holds an attribute's whole column."""
    return orig.sparkSession.createDataFrame(greatest_gaps(orig, other, attrs), "attr string, d double, n long, m long")


def entropy(df: DataFrame, attrs: list[str]) -> DataFrame:
    """attr, h: bits of entropy over an attribute's distinct values."""
    return df.sparkSession.createDataFrame(entropies([df], attrs), "attr string, h double")


def entropy_gain(orig: DataFrame, other: DataFrame, attrs: list[str]) -> DataFrame:
    """attr, h_orig, h_pert, gain. Its mean is the average information gain."""
    both = [(a, x, y, y - x) for a, x, y in entropies([orig, other], attrs)]
    return orig.sparkSession.createDataFrame(both, "attr string, h_orig double, h_pert double, gain double")


def range_share(orig: DataFrame, other: DataFrame, attrs: list[str]) -> DataFrame:
    """attr, share: the part of the other's values that lie inside the original's range."""
    ends = orig.agg(*(f(a).alias(f"{k}_{a}") for a in attrs for k, f in (("lo", F.min), ("hi", F.max))))
    row = other.join(F.broadcast(ends)).agg(*(F.avg(((F.col(a) >= F.col(f"lo_{a}")) & (F.col(a) <= F.col(f"hi_{a}"))).cast("double")).alias(f"s_{a}") for a in attrs))
    return row.select(F.inline(F.array(*(F.struct(F.lit(a).alias("attr"), F.col(f"s_{a}").alias("share")) for a in attrs))))


def bias_report(orig: DataFrame, other: DataFrame, attrs: list[str]) -> DataFrame:
    """attr, mean_shift and sd_ratio (bias A, in the original's deviations) and ks (bias D)."""
    stat = lambda df, t: df.agg(*(f(a).alias(f"{k}_{a}") for a in attrs for k, f in (("m", F.avg), ("s", F.stddev_samp)))).select(F.inline(F.array(*(F.struct(F.lit(a).alias("attr"), F.col(f"m_{a}").alias(f"m_{t}"), F.col(f"s_{a}").alias(f"s_{t}")) for a in attrs))))
    both = stat(orig, "x").join(stat(other, "y"), "attr").join(ks_attributes(orig, other, attrs), "attr")
    return both.select("attr", ((F.col("m_y") - F.col("m_x")) / F.col("s_x")).alias("mean_shift"), (F.col("s_y") / F.col("s_x")).alias("sd_ratio"), F.col("d").alias("ks"))


def correlation_shift(a: Moments, b: Moments) -> float:
    """Bias B between attributes: the largest change of a correlation."""
    return float(np.abs(a.cov - b.cov).max())


def isometry_error(matrix: DataFrame, moved: DataFrame, attrs: list[str], asked: int = 64, seed: str = "pairs") -> DataFrame:
    """pairs, max_error: how far distances change between a query set of `asked` records (a keyed draw) and all others."""
    from ..functions.rng import uniform

    rows = paired(matrix, moved, attrs)
    chosen = matrix.select(KEY).orderBy(uniform(seed, "iso", F.col(KEY)), KEY).limit(asked).withColumnRenamed(KEY, "__asked")
    left, right = rows.join(F.broadcast(chosen), F.col(KEY) == F.col("__asked")).drop("__asked").alias("l"), rows.alias("r")
    pairs = right.join(F.broadcast(left), F.col(f"l.{KEY}") != F.col(f"r.{KEY}"))
    length = lambda k: F.sqrt(sum((F.pow(F.col(f"l.{k}_{a}") - F.col(f"r.{k}_{a}"), 2) for a in attrs), F.lit(0.0)))
    return pairs.agg(F.count(F.lit(1)).alias("pairs"), F.max(F.abs(length("x") - length("y"))).alias("max_error"))


def utility_loss(acc: DataFrame) -> DataFrame:
    """From dataset, classifier, method, pct: what each method loses against Original."""
    orig = acc.where("method = 'Original'").select("dataset", "classifier", F.col("pct").alias("base"))
    return acc.where("method <> 'Original'").join(orig, ["dataset", "classifier"]).select("dataset", "classifier", "method", (F.col("base") - F.col("pct")).alias("loss"))
