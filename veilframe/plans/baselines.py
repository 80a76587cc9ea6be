"""What the method is compared with: random rotation, geometric perturbation, noise, randomized response."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.rng import gaussian_matrix, normal, uniform, uniform_of, with_keyed_normals
from .matrix import KEY, NumericMatrixSpec
from .moments import Moments, fit, standardize
from .perturb import linear
from .search import diff_variances


def identity(matrix: DataFrame) -> DataFrame:
    return matrix


def random_orthogonal(n: int, seed: str, k: int) -> np.ndarray:
    """From the QR of a keyed Gaussian matrix, signs set so that the result is uniform."""
    q, r = np.linalg.qr(gaussian_matrix(seed, f"orth{k}", n, n))
    return q * np.sign(np.diag(r))


def best_orthogonal(matrix: DataFrame, moments: Moments, iters: int, seed: str, scoring: str = "cov") -> tuple[np.ndarray, float]:
    """Of `iters` draws the one whose least-changed attribute changes most. scoring "data" reads the records for each draw."""
    drawn = [random_orthogonal(len(moments.attrs), seed, k) for k in range(iters)]
    if scoring == "cov":
        scores = [float(diff_variances(moments.cov, q).min()) for q in drawn]
    else:
        z, attrs = standardize(matrix, moments), list(moments.attrs)
        scores = [min(z.agg(*(F.var_samp(sum((F.col(attrs[j]) * float(q[i, j]) for j in range(len(attrs))), F.lit(0.0)) - F.col(attrs[i])) for i in range(len(attrs)))).first()) for q in drawn]
    k = int(np.round(scores, 9).argmax())
    return drawn[k], scores[k]


def _turned(matrix: DataFrame, m: Moments, a: np.ndarray, b: np.ndarray) -> DataFrame:
    return linear(matrix, list(m.attrs), a / m.sd, b - (a / m.sd) @ m.mean)


def _back(df: DataFrame, m: Moments) -> DataFrame:
    return df.withColumns({a: F.col(a) * float(s) + float(mu) for a, mu, s in zip(m.attrs, m.mean, m.sd, strict=True)})


def rotation(matrix: DataFrame, spec: NumericMatrixSpec, iters: int = 10, seed: str = "rp", scoring: str = "cov", moments: Moments | None = None) -> DataFrame:
    """Random rotation: standardized records times the best of ten random orthogonal matrices; key kept."""
    m = moments or fit(matrix, spec.value_cols)
    q, _ = best_orthogonal(matrix, m, iters, seed, scoring)
    return _back(_turned(matrix, m, q, np.zeros(spec.n)), m)


def geometric(matrix: DataFrame, spec: NumericMatrixSpec, iters: int = 10, sigma: float = 0.3, seed: str = "gp", scoring: str = "cov", kind: str = "keyed", moments: Moments | None = None) -> DataFrame:
    """Geometric perturbation: the same, with a random translation and Gaussian noise; key kept."""
    m = moments or fit(matrix, spec.value_cols)
    q, _ = best_orthogonal(matrix, m, iters, seed, scoring)
    shift = np.array([uniform_of(seed, "shift", "t", j) for j in range(spec.n)])
    noisy = _turned(matrix, m, q, shift)
    if kind == "keyed":
        return _back(with_keyed_normals(noisy, KEY, list(m.attrs), seed, "noise", lambda v, z: v + sigma * z), m)
    noisy = noisy.withColumns({a: F.col(a) + sigma * normal(seed, "noise", F.col(KEY), i, kind) for i, a in enumerate(m.attrs)})
    return _back(noisy, m)


def _laplace(seed: str, stream: str, key: Column, j: int) -> Column:
    u = uniform(seed, stream, key, j) - 0.5
    return -F.signum(u) * F.log(1 - 2 * F.abs(u))


def additive(matrix: DataFrame, spec: NumericMatrixSpec, sigma: float = 0.3, dist: str = "normal", seed: str = "add", moments: Moments | None = None) -> DataFrame:
    """Every value plus noise in proportion to its attribute's deviation; dist normal, uniform or laplace (unit variance each)."""
    m = moments or fit(matrix, spec.value_cols)
    draw = {"normal": lambda i: normal(seed, "noise", F.col(KEY), i), "uniform": lambda i: (uniform(seed, "noise", F.col(KEY), i) - 0.5) * float(np.sqrt(12)), "laplace": lambda i: _laplace(seed, "noise", F.col(KEY), i) / float(np.sqrt(2))}[dist]
    return matrix.withColumns({a: F.col(a) + float(sigma * s) * draw(i) for i, (a, s) in enumerate(zip(m.attrs, m.sd, strict=True))})


def randomized_response(df: DataFrame, column: str, key: Column, domain: list, p: float = 0.7, seed: str = "rr") -> DataFrame:
    """Keeps a category with probability p, else draws one of the other categories evenly."""
    others = F.array_except(F.array(*(F.lit(x) for x in domain)), F.array(F.col(column)))
    pick = F.element_at(others, (F.floor(uniform(seed, "pick", key) * F.size(others)) + 1).cast("int"))
    return df.withColumn(column, F.when(uniform(seed, "keep", key) < p, F.col(column)).otherwise(pick))


def response_estimate(answers: DataFrame, column: str, domain_size: int, p: float = 0.7) -> DataFrame:
    """column, observed, estimate: unbiased shares of the true categories."""
    q = (1 - p) / (domain_size - 1)
    n = answers.agg(F.count(F.lit(1)).alias("__n"))
    return answers.groupBy(column).agg(F.count(F.lit(1)).alias("c")).join(F.broadcast(n)).select(column, (F.col("c") / F.col("__n")).alias("observed"), ((F.col("c") / F.col("__n") - q) / (p - q)).alias("estimate"))


def laplace_value(df: DataFrame, column: str, key: Column, low: float, high: float, epsilon: float, seed: str = "ldp") -> DataFrame:
    """A bounded value under local differential privacy."""
    inside = F.least(F.greatest(F.col(column), F.lit(low)), F.lit(high))
    return df.withColumn(column, inside + (high - low) / epsilon * _laplace(seed, "ldp", key, 0))


def laplace_query(answers: DataFrame, column: str, key: Column, sensitivity: float, epsilon: float, seed: str = "gdp") -> DataFrame:
    """Answers of an aggregate query with Laplace noise."""
    return answers.withColumn(column, F.col(column) + sensitivity / epsilon * _laplace(seed, "gdp", key, 0))
