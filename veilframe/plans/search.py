"""Search of the reflection axis and the angle: the least-protected attribute of a candidate decides.

phi(axis, angle) is the least variance, over attributes, of perturbed minus original standardized values.
It follows from the covariance of the standardized attributes alone: for row r of the rotation with the
axis's column negated, Var = r C r', Cov with the original = r C_i, and the difference has variance
C_ii + Var - 2 Cov. Negating one column changes both by terms of that column only, so all axes of an angle
cost one matrix product. form="printed" adds one covariance instead of taking two away, as a variant.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import geometry

PLACES = 9
#: Records whose gaps for all angles a scan holds at a time.
ROWS_AT_ONCE = 256
SELECTIONS = ("maximin", "global_max", "maximin_best_axis")


@dataclass(frozen=True)
class Choice:
    theta: float
    axis: int  # 1-based
    phi_opt: float  # the guarantee that the selection maximizes
    phi_chosen: float  # phi of the chosen candidate


def var_from_cov(cov: np.ndarray, a: np.ndarray) -> np.ndarray:
    return np.einsum("ij,jk,ik->i", a, cov, a)


def cross_from_cov(cov: np.ndarray, a: np.ndarray) -> np.ndarray:
    return np.einsum("ij,ji->i", a, cov)


def diff_variances(cov: np.ndarray, a: np.ndarray, form: str = "exact") -> np.ndarray:
    """Variance of moved minus original, for each attribute."""
    cross = cross_from_cov(cov, a)
    return np.diag(cov) + var_from_cov(cov, a) + (cross if form == "printed" else -2 * cross)


def grid_cov(cov: np.ndarray, degrees: list[float] | None = None, form: str = "exact", reflection: str = "single") -> np.ndarray:
    """phi by (axis, angle)."""
    degrees = tuple(degrees if degrees is not None else geometry.angles())
    n = len(cov)
    out = np.empty((n, len(degrees)))
    for first in range(0, len(degrees), 32):
        r = geometry.cached_rotations(n, degrees[first : first + 32])
        g = r @ cov
        plain = (g * r).sum(axis=2)  # variances without reflection
        cross = (r * cov).sum(axis=2)
        var = plain[:, :, None] - 4 * r * (g - r * np.diag(cov))  # angle, attribute, axis
        crossed = cross[:, :, None] - 2 * r * cov
        if reflection == "complement":
            crossed = -crossed
        total = np.diag(cov)[None, :, None] + var + (crossed if form == "printed" else -2 * crossed)
        out[:, first : first + 32] = total.min(axis=1).T
    return out


def grid_df(spark: SparkSession, grid: np.ndarray, degrees: list[float]) -> DataFrame:
    rows = [(a + 1, int(d), float(grid[a, k])) for a in range(len(grid)) for k, d in enumerate(degrees)]
    return spark.createDataFrame(rows, "axis int, theta_deg int, phi double")


def rotation_df(spark: SparkSession, n: int, degrees: list[int]) -> DataFrame:
    r = geometry.rotations(n, tuple(degrees))
    return spark.createDataFrame([(int(d), i + 1, j + 1, float(r[k, i, j])) for k, d in enumerate(degrees) for i in range(n) for j in range(n)], "theta_deg int, i int, j int, r double")


def grid_cov_df(cov: DataFrame, rotations: DataFrame, n: int, form: str = "exact", reflection: str = "single") -> DataFrame:
    """The relational twin of grid_cov, for few attributes. cov: i, j, cov; rotations: theta_deg, i, j, r (both n * n small)."""
    axes = cov.sparkSession.range(1, n + 1).select(F.col("id").cast("int").alias("axis"))
    sign = F.when(F.col("j") == F.col("axis"), -1.0).otherwise(1.0) * (-1.0 if reflection == "complement" else 1.0)
    a = rotations.join(F.broadcast(axes)).select("theta_deg", "axis", "i", "j", (F.col("r") * sign).alias("a"))
    c = F.broadcast(cov)
    var = a.alias("x").join(c.alias("c"), F.col("x.j") == F.col("c.i")).join(F.broadcast(a.alias("y")), (F.col("x.theta_deg") == F.col("y.theta_deg")) & (F.col("x.axis") == F.col("y.axis")) & (F.col("x.i") == F.col("y.i")) & (F.col("c.j") == F.col("y.j")))
    var = var.groupBy("x.theta_deg", "x.axis", "x.i").agg(F.sum(F.col("x.a") * F.col("c.cov") * F.col("y.a")).alias("v"))
    cross = a.alias("x").join(c.alias("c"), (F.col("x.i") == F.col("c.i")) & (F.col("x.j") == F.col("c.j"))).groupBy("theta_deg", "axis", "x.i").agg(F.sum(F.col("a") * F.col("cov")).alias("s"))
    weight = 1.0 if form == "printed" else -2.0
    return var.join(cross, ["theta_deg", "axis", "i"]).groupBy("axis", "theta_deg").agg(F.min(1.0 + F.col("v") + weight * F.col("s")).alias("phi"))


def candidates(n: int, degrees: list[float]) -> list[tuple[int, float]]:
    return [(a, d) for a in range(1, n + 1) for d in degrees]


def grid_scan(df: DataFrame, attrs: list[str], shift: np.ndarray, degrees: list[float] | None = None, strategy: str = "batched", reflection: str = "single") -> np.ndarray:
    """phi by (axis, angle) from the standardized records themselves.

    "loop" transforms the table and aggregates once for every candidate, as the basic method does; "batched"
    scores all candidates in one pass and adds up counts, sums and squares by (candidate, attribute). There every
    record is turned once for an angle; negating an axis changes its gaps by that axis's value times a number."""
    degrees = list(degrees if degrees is not None else geometry.angles())
    n, kinds = len(attrs), candidates(len(attrs), degrees)
    if strategy == "loop":
        out = []
        for axis, d in kinds:
            a, b = geometry.compose(geometry.rotation(n, d), shift, geometry.reflection(n, axis, reflection))
            gap = [sum((F.col(attrs[j]) * float(a[i, j]) for j in range(n)), F.lit(float(b[i]))) - F.col(attrs[i]) for i in range(n)]
            out.append(min(df.agg(*(F.var_samp(g) for g in gap)).first()))
        return np.array(out).reshape(n, len(degrees))
    if strategy != "batched":
        raise ValueError(f"strategy is batched or loop, not {strategy}")
    r = geometry.rotations(n, tuple(degrees))
    side = -1.0 if reflection == "complement" else 1.0
    turned = (side * r - np.eye(n)).reshape(-1, n).T  # columns by (angle, attribute): the gap that no axis is negated for
    moved = (r @ shift).ravel()
    flip = -2 * side * r  # by (angle, attribute, axis): what the axis's value adds to that gap once it is negated

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count, sums, squares = 0, np.zeros(len(moved)), np.zeros(len(moved))
        crossed, own, whole = np.zeros((len(moved), n)), np.zeros(n), np.zeros(n)
        for batch in batches:
            every = np.column_stack([batch.column(i).to_numpy(zero_copy_only=False) for i in range(n)])
            for first in range(0, len(every), ROWS_AT_ONCE):
                x = every[first : first + ROWS_AT_ONCE]
                gap = x @ turned
                gap += moved
                count, sums, crossed = count + len(x), sums + gap.sum(axis=0), crossed + gap.T @ x
                squares += np.einsum("ij,ij->j", gap, gap)
                own, whole = own + (x * x).sum(axis=0), whole + x.sum(axis=0)
        if count:
            by = lambda v: v.reshape(len(degrees), n, -1)
            added = by(sums) + flip * whole
            second = by(squares) + 2 * flip * by(crossed) + flip * flip * own
            flat = np.concatenate([[count], *(v.transpose(2, 0, 1).ravel() for v in (added, second))])
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat)), pa.int32()), pa.array(flat)], names=["at", "v"])

    rows = df.select(*attrs).mapInArrow(work, "at int, v double").groupBy("at").agg(F.sum("v").alias("v")).collect()
    flat = np.zeros(1 + 2 * len(kinds) * n)
    for row in rows:
        flat[row["at"]] = row["v"]
    m, (s, q) = flat[0], flat[1:].reshape(2, len(kinds), n)
    return ((q - s * s / m) / (m - 1)).min(axis=1).reshape(n, len(degrees))


def select(grid: np.ndarray, degrees: list[float], selection: str = "maximin") -> Choice:
    """The chosen candidate. Values count to PLACES decimals; ties go to the smaller angle, then the smaller axis.

    maximin: the worst axis of each angle, the best of these angles, and that worst axis. maximin_best_axis:
    the same angle with its best axis. global_max: the best candidate of all."""
    g = np.round(grid, PLACES)
    if selection == "global_max":
        k = int(g.max(axis=0).argmax())
        axis = int(g[:, k].argmax())
        return Choice(degrees[k], axis + 1, float(g[axis, k]), float(g[axis, k]))
    if selection not in SELECTIONS:
        raise ValueError(f"selection is one of {SELECTIONS}")
    worst = g.min(axis=0)
    k = int(worst.argmax())
    axis = int(g[:, k].argmin() if selection == "maximin" else g[:, k].argmax())
    return Choice(degrees[k], axis + 1, float(worst[k]), float(g[axis, k]))


def select_df(grid: DataFrame, selection: str = "maximin") -> DataFrame:
    """The relational twin of select(): theta_deg, axis, phi_opt."""
    g = grid.withColumn("phi", F.round("phi", PLACES))
    if selection == "global_max":
        return g.orderBy(F.desc("phi"), "theta_deg", "axis").limit(1).select("theta_deg", "axis", F.col("phi").alias("phi_opt"))
    axis = F.min(F.struct("phi", "axis"))["axis"] if selection == "maximin" else F.min(F.struct((-F.col("phi")).alias("p"), "axis"))["axis"]
    by = g.groupBy("theta_deg").agg(F.min("phi").alias("phi_opt"), axis.alias("axis"))
    return by.orderBy(F.desc("phi_opt"), "theta_deg").limit(1).select("theta_deg", "axis", "phi_opt")


def curve_global(grid: DataFrame) -> DataFrame:
    """For each angle the worst axis's phi."""
    return grid.groupBy("theta_deg").agg(F.min("phi").alias("phi"))


def curve_axis(grid: DataFrame, n: int) -> DataFrame:
    """theta_deg and a column for each axis."""
    return grid.groupBy("theta_deg").pivot("axis", list(range(1, n + 1))).agg(F.first("phi")).select("theta_deg", *(F.col(str(i)).alias(f"axis_{i}") for i in range(1, n + 1)))


def satisfies_separation(phis: DataFrame, tolerance: float = 1e-9) -> DataFrame:
    """Of candidate releases (label, phi, chosen): whether the chosen one's phi is the largest of all."""
    best = phis.withColumn("phi_max", F.max("phi").over(Window.partitionBy(F.lit(0))))
    return best.where("chosen").select("label", "phi", "phi_max", (F.col("phi") >= F.col("phi_max") - tolerance).alias("separated"))
