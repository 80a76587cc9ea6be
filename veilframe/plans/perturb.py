"""The release itself: standardize, move, expand, rescale, shuffle; and the whole method in one call.

Fitting reads the records once (twice for many attributes: a pilot of 1,000 rows first); releasing is one
projection and, for the order of the rows, one exchange. Standardizing folds into the literals of the move.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import asdict, dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.rng import normal, uniform, with_keyed_normals
from . import geometry, search
from .matrix import KEY, NumericMatrixSpec, as_matrix
from .moments import Moments, correlation, fit, standardize

WIDE = 12
STEPS = ("reflect", "translate", "rotate", "expand")


@dataclass(frozen=True)
class PerturbationModel:
    """All that a release needs. Its seed and shift are the owner's secrets: store it apart from releases."""

    attrs: tuple[str, ...]
    mean: tuple[float, ...]
    sd: tuple[float, ...]
    theta: float
    axis: int
    shift: tuple[float, ...]
    sigma: float = 0.3
    seed: str = "smp"
    phi_opt: float = float("nan")
    form: str = "exact"
    selection: str = "maximin"
    reflection: str = "single"
    constant: tuple[str, ...] = ()
    steps: tuple[str, ...] = STEPS
    extra: dict = field(default_factory=dict)

    def affine(self) -> tuple[np.ndarray, np.ndarray]:
        n = len(self.attrs)
        turn = geometry.rotation(n, self.theta) if "rotate" in self.steps else np.eye(n)
        signs = geometry.reflection(n, self.axis, self.reflection) if "reflect" in self.steps else np.ones(n)
        return geometry.compose(turn, np.array(self.shift) if "translate" in self.steps else np.zeros(n), signs)

    def save(self, spark: SparkSession, path: str) -> None:
        spark.createDataFrame([(json.dumps(asdict(self)),)], "value string").coalesce(1).write.mode("overwrite").text(path)

    @staticmethod
    def load(spark: SparkSession, path: str) -> PerturbationModel:
        got = json.loads(spark.read.text(path).first()["value"])
        return PerturbationModel(**{k: tuple(v) if isinstance(v, list) else v for k, v in got.items()})

    def check(self, columns: list[str]) -> None:
        if missing := [a for a in self.attrs if a not in columns]:
            raise ValueError(f"the table has changed: no {missing}")


def fit_model(df: DataFrame, spec: NumericMatrixSpec, sigma: float = 0.3, search_by: str = "cov", form: str = "exact", selection: str = "maximin", reflection: str = "single", degrees: list[float] | None = None, seed: str = "smp", ddof: int = 1, shift: np.ndarray | None = None, params: tuple[float, int] | None = None, steps: tuple[str, ...] = STEPS, strategy: str = "batched", moments: Moments | None = None) -> PerturbationModel:
    """Chooses the parameters for a matrix of as_matrix(). Constant attributes are left out and pass unperturbed."""
    degrees = list(degrees if degrees is not None else geometry.angles())
    m = moments or fit(df, spec.value_cols, ddof)
    live = [i for i, s in enumerate(m.sd) if s > 0]
    attrs, cov = [m.attrs[i] for i in live], m.cov[np.ix_(live, live)]
    if not attrs:
        raise ValueError("no attribute varies")
    moving = np.asarray(shift, dtype=float)[live] if shift is not None else geometry.translation(len(m.attrs), seed)[live]
    own = Moments(tuple(attrs), m.rows, m.mean[live], m.sd[live], cov)
    if params is not None:
        theta, axis = params
        n = len(attrs)
        a = geometry.rotation(n, theta) * geometry.reflection(n, axis, reflection)
        choice = search.Choice(theta, axis, float(search.diff_variances(cov, a, form).min()), float("nan"))
    else:
        grid = search.grid_cov(cov, degrees, form, reflection) if search_by == "cov" else search.grid_scan(standardize(df, own), attrs, moving, degrees, strategy, reflection)
        choice = search.select(grid, degrees, selection)
    return PerturbationModel(tuple(attrs), tuple(own.mean.tolist()), tuple(own.sd.tolist()), choice.theta, choice.axis, tuple(moving.tolist()), sigma, seed, choice.phi_opt, form, selection, reflection, tuple(m.constant), steps)


def move(df: DataFrame, model: PerturbationModel, standardized: bool = False) -> DataFrame:
    """Reflected, shifted and rotated standardized values. Over WIDE attributes: matrix products on Arrow batches."""
    a, b = model.affine()
    mean, sd = (np.zeros(len(b)), np.ones(len(b))) if standardized else (np.array(model.mean), np.array(model.sd))
    return linear(df, list(model.attrs), a / sd, b - (a / sd) @ mean)


def linear(df: DataFrame, attrs: list[str], a: np.ndarray, b: np.ndarray) -> DataFrame:
    """attrs become A attrs + b; other columns stay."""
    n = len(attrs)
    if n <= WIDE:
        made = [sum((F.col(f"`{attrs[j]}`") * float(a[i, j]) for j in range(n)), F.lit(float(b[i]))).alias(attrs[i]) for i in range(n)]
        return df.select(*(made[attrs.index(c)] if c in attrs else F.col(f"`{c}`") for c in df.columns))
    where = [df.columns.index(c) for c in attrs]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.column_stack([batch.column(i).to_numpy(zero_copy_only=False) for i in where]) @ a.T + b
            columns = list(batch.columns)
            for k, i in enumerate(where):
                columns[i] = pa.array(x[:, k])
            yield pa.RecordBatch.from_arrays(columns, names=batch.schema.names)

    return df.mapInArrow(work, df.schema)


def expand(df: DataFrame, attrs: list[str] | tuple[str, ...], sigma: float = 0.3, seed: str = "smp", kind: str = "keyed") -> DataFrame:
    """Pushes every value away from zero by the size of a normal draw; zero stays. Keyed draws are made on Arrow batches."""
    if not sigma:
        return df
    if kind == "keyed":
        return with_keyed_normals(df, KEY, list(attrs), seed, "noise", lambda v, z: v + np.sign(v) * np.abs(float(sigma) * z))
    return df.withColumns({a: F.col(a) + F.signum(a) * F.abs(F.lit(float(sigma)) * normal(seed, "noise", F.col(KEY), i, kind)) for i, a in enumerate(attrs)})


def rescale(df: DataFrame, model: PerturbationModel) -> DataFrame:
    return df.withColumns({a: F.col(a) * s + m for a, m, s in zip(model.attrs, model.mean, model.sd, strict=True)})


def shuffle(df: DataFrame, seed: str = "smp", mode: str = "global", attrs: tuple[str, ...] = (), kind: str = "keyed") -> DataFrame:
    """Random row order by a keyed draw, and no key any more.

    global: a total order by ranges; block: random partitions, each in random order (one exchange, no sampling
    of ranges); sorted: ascending by the attributes, for studies; none: rows and key stay as they are."""
    if mode == "none":
        return df
    if mode == "sorted":
        return df.orderBy(*attrs).drop(KEY)
    draw = df.withColumn("__u", uniform(seed, "order", F.col(KEY), 0, kind))
    if mode == "global":
        draw = draw.orderBy("__u", KEY)
    elif mode == "block":
        draw = draw.repartition("__u").sortWithinPartitions("__u", KEY)
    else:
        raise ValueError(f"shuffle is global, block, sorted or none, not {mode}")
    return draw.drop("__u", KEY)


def release(matrix: DataFrame, model: PerturbationModel, order: str = "global", kind: str = "keyed") -> DataFrame:
    """The released table from a matrix of as_matrix() and a model."""
    model.check(matrix.columns)
    out = move(matrix, model)
    if "expand" in model.steps:
        out = expand(out, model.attrs, model.sigma, model.seed, kind)
    return shuffle(rescale(out, model), model.seed, order, model.attrs, kind)


def smp(df: DataFrame, spec: NumericMatrixSpec, sigma: float = 0.3, search_by: str = "cov", order: str = "block", kind: str = "fast", on_null: str = "error", **how) -> DataFrame:
    """The whole method in one call; search_by "cov" or "scan". kind="keyed" draws what SQL can draw as well."""
    matrix = as_matrix(df, spec, on_null)
    return release(matrix, fit_model(matrix, spec, sigma, search_by, **how), order, kind)


def release_series(df: DataFrame, spec: NumericMatrixSpec, sigmas: list[float], seed: str = "smp", **how) -> list[DataFrame]:
    """Repeated releases: every one draws anew and with more noise than the one before."""
    if any(b <= a for a, b in zip(sigmas, sigmas[1:], strict=False)):
        raise ValueError("sigmas must rise from release to release")
    return [smp(df, spec, sigma, seed=f"{seed}-{k}", **how) for k, sigma in enumerate(sigmas)]


def smp_grouped(df: DataFrame, spec: NumericMatrixSpec, group: str, sigma: float = 0.3, seed: str = "smp", least: int = 3) -> DataFrame:
    """A fit of its own for every group; moments by group in one aggregation, parameters joined back.

    Groups of fewer than `least` records are not released. Constant attributes of a group pass unperturbed."""
    n, attrs = spec.n, list(spec.value_cols)
    if n > 8:
        raise ValueError("grouped fits are for up to eight attributes")
    matrix = as_matrix(df, NumericMatrixSpec(spec.value_cols, spec.key_cols, spec.class_col, tuple({*spec.passthrough, group})))
    pairs = [(i, j) for i in range(n) for j in range(i + 1, n)]
    stats = matrix.groupBy(group).agg(F.count(F.lit(1)).alias("rows"), F.array(*(F.avg(a) for a in attrs)).alias("mean"), F.array(*(F.coalesce(F.stddev_samp(a), F.lit(0.0)) for a in attrs)).alias("sd"), F.array(*([F.coalesce(correlation(attrs[i], attrs[j]), F.lit(0.0)) for i, j in pairs] or [F.lit(0.0)])).alias("corr")).where(F.col("rows") >= least)
    shift = geometry.translation(n, seed)
    degrees = geometry.angles()

    def solve(frames):
        for f in frames:
            a_out, b_out = [], []
            for mean, sd, corr in zip(f["mean"], f["sd"], f["corr"], strict=True):
                sd, cov = np.array(sd), np.eye(n)
                for (i, j), c in zip(pairs, corr, strict=False):
                    cov[i, j] = cov[j, i] = c
                live = np.flatnonzero(sd > 0)
                a, b = np.eye(n), np.zeros(n)
                if len(live):
                    got = search.select(search.grid_cov(cov[np.ix_(live, live)], degrees), degrees)
                    la, lb = geometry.compose(geometry.rotation(len(live), got.theta), shift[live], geometry.reflection(len(live), got.axis))
                    a[np.ix_(live, live)], b[live] = la / sd[live], lb - (la / sd[live]) @ np.array(mean)[live]
                a_out.append(a.ravel().tolist()), b_out.append(b.tolist())
            yield f[[group, "mean", "sd"]].assign(a=a_out, b=b_out)

    kind = matrix.schema[group].dataType.simpleString()
    params = stats.mapInPandas(solve, f"`{group}` {kind}, mean array<double>, sd array<double>, a array<double>, b array<double>")
    wide = matrix.join(params.withColumnRenamed(group, "__group"), F.col(group).eqNullSafe(F.col("__group")))
    moved = wide.select(KEY, *spec.kept, *([group] if group not in spec.kept else []), "mean", "sd", *(F.when(F.col("sd")[i] > 0, sum((F.col(attrs[j]) * F.col("a")[i * n + j] for j in range(n)), F.col("b")[i])).otherwise(F.col(attrs[i])).alias(attrs[i]) for i in range(n)))
    noise = lambda i, a: F.signum(a) * F.abs(F.lit(float(sigma)) * normal(seed, "noise", F.col(KEY), i))
    back = moved.withColumns({a: F.when(F.col("sd")[i] > 0, (F.col(a) + noise(i, a)) * F.col("sd")[i] + F.col("mean")[i]).otherwise(F.col(a)) for i, a in enumerate(attrs)})
    return shuffle(back.drop("mean", "sd"), seed, "block")
