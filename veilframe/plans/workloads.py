"""The experiments, re-expressed on the given tables. Each returns a tidy table of measured values."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import attacks, baselines, classify, datasets, geometry, metrics, search
from .held import gathered, hold, holding, settled
from .matrix import KEY, NumericMatrixSpec, as_matrix
from .moments import Moments, fit
from .perturb import STEPS, fit_model, release
from .places import slots_for

METHODS = ("RP", "GP", "SMP")


def load(spark: SparkSession, folder: str, name: str) -> tuple[DataFrame, NumericMatrixSpec, Moments]:
    df, spec = datasets.DATASETS[name](spark, folder)
    matrix = hold(as_matrix(df, spec))
    m = fit(matrix, spec.value_cols)
    if m.constant:
        spec = spec.only([c for c in spec.value_cols if c not in m.constant])
        matrix = matrix.drop(*m.constant)
        m = fit(matrix, spec.value_cols)
    return gathered(matrix, m.rows), spec, m


def version(matrix: DataFrame, spec: NumericMatrixSpec, m: Moments, method: str, sigma: float = 0.3, **how) -> DataFrame:
    """A data set as it is, or perturbed by a method, its key kept for the evaluator."""
    if method == "Original":
        return matrix
    if method == "RP":
        return baselines.rotation(matrix, spec, moments=m)
    if method == "GP":
        return baselines.geometric(matrix, spec, sigma=sigma, moments=m)
    return release(matrix, fit_model(matrix, spec, sigma, moments=m, **how), "none")


def beside(matrix: DataFrame, spec: NumericMatrixSpec, m: Moments, method: str, sigma: float = 0.3, kept: tuple[str, ...] = (), **how) -> DataFrame:
    """Every record with its version in the same row: the key, x_<attr>, y_<attr>, what is to be kept, and __place where
    the records have it. No join, so repeated keys do no harm."""
    attrs = list(spec.value_cols)
    rows = version(matrix.withColumns({f"x_{a}": F.col(a) for a in attrs}), spec, m, method, sigma, **how)
    placed = ["__place"] if "__place" in matrix.columns else []
    return hold(rows.select(KEY, *(f"x_{a}" for a in attrs), *(F.col(a).alias(f"y_{a}") for a in attrs), *kept, *placed))


def side(pairs: DataFrame, k: str, attrs: list[str], also: tuple[str, ...] = ()) -> DataFrame:
    """One side of beside(), under the attributes' names."""
    return pairs.select(*also, *(F.col(f"{k}_{a}").alias(a) for a in attrs))


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def accuracy_study(spark: SparkSession, folder: str, names: tuple[str, ...] = datasets.STUDIED, algorithms: tuple[str, ...] = ("knn", "nb", "tree"), folds: int = 10, run: int | None = None) -> DataFrame:
    """dataset, method, classifier, pct: cross-validated, trained and tested on the same version."""
    parts = []
    for name in names:
        with holding():
            matrix, spec, m = load(spark, folder, name)
            for method in ("Original", *METHODS):
                rows = hold(version(matrix, spec, m, method))
                for algorithm in algorithms:
                    got = classify.cv_native(rows, spec, folds, "nb") if algorithm == "nb" and run is None else classify.cv_accuracy(rows, spec, algorithm, folds, run)
                    parts.append(settled(got.agg(F.avg(100.0 * F.col("correct") / F.col("total")).alias("pct")).select(F.lit(name).alias("dataset"), F.lit(method).alias("method"), F.lit(algorithm).alias("classifier"), "pct")))
    return _union(parts)


def resistance_study(spark: SparkSession, folder: str, names: tuple[str, ...] = datasets.STUDIED, kinds: tuple[str, ...] = ("ni", "ica", "io"), pairings: tuple[str, ...] = ("true", "released"), methods: tuple[str, ...] = METHODS) -> DataFrame:
    """dataset, method, attack, pairing, std_min, std_avg. Every method meets the attacker in the same pairings: by the
    hidden key, and by place after a shuffle."""
    run = {"ni": attacks.naive, "ica": attacks.ica, "io": attacks.known_io}
    parts = []
    for name in names:
        with holding():
            matrix, spec, m = load(spark, folder, name)
            attrs = list(spec.value_cols)
            placed = matrix
            if "released" in pairings:
                slots = slots_for(m.rows, 64)
                x = hold(gathered(attacks.numbered(matrix, "first", slots).select(KEY, *(F.col(a).alias(f"x_{a}") for a in attrs), "__place"), m.rows))
                placed = hold(gathered(attacks.numbered(matrix, "order", slots), m.rows))
            for method in methods:
                both = beside(placed, spec, m, method)
                rows = side(both, "y", attrs)
                my = fit(rows, attrs)
                for pairing in pairings:
                    pairs = both.drop("__place") if pairing == "true" else hold(gathered(x.join(both.select(*(f"y_{a}" for a in attrs), "__place"), "__place").drop("__place"), m.rows))
                    for kind in kinds:
                        got = run[kind](matrix, rows, attrs, pairs=pairs, sides=(m, my))
                        parts.append(settled(got.select(F.lit(name).alias("dataset"), F.lit(method).alias("method"), F.lit(kind).alias("attack"), F.lit(pairing).alias("pairing"), "std_min", "std_avg")))
    return _union(parts)


def resistance_ranks(study: DataFrame) -> DataFrame:
    """The rank test over all (dataset, attack, measure) blocks of a resistance study, for each pairing by itself."""
    long = study.unpivot(["dataset", "method", "attack", "pairing"], ["std_min", "std_avg"], "measure", "v")
    return _union([metrics.friedman(long.where(F.col("pairing") == p), ["dataset", "attack", "measure"], "method", "v").withColumn("pairing", F.lit(p)) for p in ("true", "released")])


def accuracy_ranks(study: DataFrame) -> DataFrame:
    return metrics.friedman(study.where("method <> 'Original'").withColumnRenamed("pct", "v"), ["dataset", "classifier"], "method", "v")


def guarantee_dynamics(spark: SparkSession, folder: str, name: str = "cust_spend", degrees: tuple[int, ...] = tuple(range(5, 180, 10))) -> DataFrame:
    """theta_deg, axis, phi, std_min, std_avg of naive estimation, with the best axis of every angle and no noise."""
    matrix, spec, m = load(spark, folder, name)
    attrs = list(spec.value_cols)
    grid = search.grid_cov(m.cov, list(degrees))
    parts = []
    for k, theta in enumerate(degrees):
        axis = int(np.round(grid[:, k], 9).argmax()) + 1
        rows = release(matrix, fit_model(matrix, spec, 0.0, moments=m, params=(theta, axis)), "none")
        parts.append(attacks.naive(matrix, rows, attrs).select(F.lit(theta).alias("theta_deg"), F.lit(axis).alias("axis"), F.lit(float(grid[axis - 1, k])).alias("phi"), "std_min", "std_avg"))
    return _union(parts)


def sigma_sweep(spark: SparkSession, folder: str, name: str = "li9", sigmas: tuple[float, ...] = (0.0, 0.3, 0.6, 1.0), folds: int = 10, run: int | None = 1) -> DataFrame:
    """sigma, std_min (of released minus original, in the original's deviations), pct of the nearest neighbour."""
    parts = []
    with holding():
        matrix, spec, m = load(spark, folder, name)
        attrs = list(spec.value_cols)
        for sigma in sigmas:
            pairs = beside(matrix, spec, m, "SMP", sigma, kept=tuple(spec.kept))
            rows = side(pairs, "y", attrs, (KEY, *spec.kept))
            low = attacks.naive(matrix, rows, attrs, scale="orig", pairs=pairs, sides=(m, m)).select(F.lit(sigma).alias("sigma"), "std_min")
            acc = classify.cv_accuracy(rows, spec, "knn", folds, run).agg(F.avg(100.0 * F.col("correct") / F.col("total")).alias("pct"))
            parts.append(settled(low.join(F.broadcast(acc))))
    return _union(parts)


def selection_ablation(spark: SparkSession, folder: str, names: tuple[str, ...] = datasets.STUDIED) -> DataFrame:
    """dataset, form, selection, theta_deg, axis, phi_opt, and the exact phi of what was chosen."""
    rows, degrees = [], geometry.angles()
    for name in names:
        _, _, m = load(spark, folder, name)
        exact = np.round(search.grid_cov(m.cov, degrees), search.PLACES)
        for form in ("exact", "printed"):
            grid = search.grid_cov(m.cov, degrees, form)
            for selection in search.SELECTIONS:
                c = search.select(grid, degrees, selection)
                rows.append((name, form, selection, int(c.theta), c.axis, round(c.phi_opt, 6), float(exact[c.axis - 1, degrees.index(c.theta)])))
    return spark.createDataFrame(rows, "dataset string, form string, selection string, theta_deg int, axis int, phi_opt double, phi_exact double")


def step_ablation(spark: SparkSession, folder: str, name: str = "doc_letters") -> DataFrame:
    """steps, std_min, std_avg, pct (naive Bayes) for every prefix of the method's steps."""
    parts = []
    with holding():
        matrix, spec, m = load(spark, folder, name)
        attrs = list(spec.value_cols)
        for k in range(1, len(STEPS) + 1):
            rows = hold(release(matrix, fit_model(matrix, spec, moments=m, steps=STEPS[:k]), "none"))
            acc = classify.cv_native(rows, spec).agg(F.avg(100.0 * F.col("correct") / F.col("total")).alias("pct"))
            parts.append(settled(attacks.naive(matrix, rows, attrs).select(F.lit("+".join(STEPS[:k])).alias("steps"), "std_min", "std_avg").join(F.broadcast(acc))))
    return _union(parts)


def entropy_study(spark: SparkSession, folder: str, names: tuple[str, ...] = datasets.STUDIED) -> DataFrame:
    """dataset, gain: mean gain in entropy over attributes."""
    parts = []
    for name in names:
        with holding():
            matrix, spec, m = load(spark, folder, name)
            attrs = list(spec.value_cols)
            pairs = beside(matrix, spec, m, "SMP")
            parts.append(settled(metrics.entropy_gain(side(pairs, "x", attrs), side(pairs, "y", attrs), attrs).agg(F.avg("gain").alias("gain")).select(F.lit(name).alias("dataset"), "gain")))
    return _union(parts)


def tuple_ks_study(spark: SparkSession, folder: str, names: tuple[str, ...] = datasets.STUDIED) -> DataFrame:
    """dataset, total, kept, pct: records whose values are not told apart from their release's."""
    parts = []
    for name in names:
        with holding():
            matrix, spec, m = load(spark, folder, name)
            got = metrics.ks_tuples(beside(matrix, spec, m, "SMP"), m).agg(F.count(F.lit(1)).alias("total"), F.sum((~F.col("rejected")).cast("long")).alias("kept"))
            parts.append(settled(got.select(F.lit(name).alias("dataset"), "total", "kept", (100.0 * F.col("kept") / F.col("total")).alias("pct"))))
    return _union(parts)


def attribute_ks_study(spark: SparkSession, folder: str, names: tuple[str, ...] = datasets.STUDIED, alpha: float = 0.05) -> DataFrame:
    """dataset, attr, d, rejected: whether an attribute's released values are told apart from the original's."""
    parts = []
    c = float(np.sqrt(-0.5 * np.log(alpha / 2)))
    for name in names:
        with holding():
            matrix, spec, m = load(spark, folder, name)
            attrs = list(spec.value_cols)
            pairs = beside(matrix, spec, m, "SMP")
            got = metrics.ks_attributes(side(pairs, "x", attrs), side(pairs, "y", attrs), attrs)
            parts.append(settled(got.select(F.lit(name).alias("dataset"), "attr", "d", (F.col("d") > c * F.sqrt((F.col("n") + F.col("m")) / (F.col("n") * F.col("m")))).alias("rejected"))))
    return _union(parts)


def phi_curves(spark: SparkSession, folder: str, name: str = "cust_spend") -> DataFrame:
    """axis, theta_deg, phi over all whole degrees."""
    _, _, m = load(spark, folder, name)
    degrees = geometry.angles(include_special=True)
    return search.grid_df(spark, search.grid_cov(m.cov, degrees), degrees)
