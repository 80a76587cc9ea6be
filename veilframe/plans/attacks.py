"""Reconstruction attacks on a release, each giving an estimate of the original to be measured by metrics.resistance.

pairing "true" sets a record against its own release (by the hidden key, the worst case); "released" sets the
k-th released row against the k-th original, as one would without a key. Membership inference (needs access to a
model) and minimality (nothing is generalized) do not apply to released tables of this kind and are not built.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.rng import gaussian_matrix, uniform
from .matrix import KEY
from .metrics import paired, resistance
from .moments import Moments, fit, standardize
from .perturb import linear
from .places import ranked, slots_for


def by_place(orig: DataFrame, released: DataFrame, attrs: list[str], seed: str = "place", slots: int | None = None) -> DataFrame:
    """Pairs rows by their place, each table in the order of a keyed draw of its own.

    Places are two-level (slots of the draw's range, by default as many as the rows need, then rows inside a slot)."""
    slots = slots or slots_for(orig.count(), 64)
    x = numbered(orig, "first", slots, seed).select(KEY, *(F.col(a).alias(f"x_{a}") for a in attrs), "__place")
    y = numbered(released, "order", slots, seed).select(*(F.col(a).alias(f"y_{a}") for a in attrs), "__place")
    return x.join(y, "__place").drop("__place")


def numbered(df: DataFrame, stream: str, slots: int, seed: str = "place") -> DataFrame:
    """df with __place, each row's place in the order of a keyed draw: "first" for originals, "order" for released rows.

    A place depends on the key alone, so every release of a table has the same."""
    rows = df.withColumn("__u", uniform(seed, stream, F.col(KEY))).withColumn("__slot", F.floor(F.col("__u") * slots).cast("int"))
    return ranked(rows, "__slot", ["__u", KEY], "__place").drop("__u", "__slot")


def pair(orig: DataFrame, released: DataFrame, attrs: list[str], pairing: str = "true") -> DataFrame:
    return paired(orig, released, attrs) if pairing == "true" else by_place(orig, released, attrs)


def naive(orig: DataFrame, released: DataFrame, attrs: list[str], pairing: str = "true", scale: str = "both", pairs: DataFrame | None = None, sides: tuple[Moments, Moments] | None = None) -> DataFrame:
    """Takes the release itself for the original. pairs: those of pair(), where several attacks share them; sides: the
    moments of originals and release, where they are known."""
    return resistance(pairs or pair(orig, released, attrs, pairing), attrs, scale, sides)


def known_io_fit(pairs: DataFrame, attrs: list[str], mx: Moments, my: Moments, solver: str = "lstsq") -> tuple[np.ndarray, np.ndarray]:
    """(A, b) with original = A released + b on standardized values, from known pairs.

    lstsq: the best linear map; procrustes: the best rotation. Only cross products reach the driver."""
    n = len(attrs)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        size = 2 * n + 1
        total = np.zeros((size, size))
        for batch in batches:
            v = np.column_stack([batch.column(i).to_numpy(zero_copy_only=False) for i in range(2 * n)])
            v = (v - np.concatenate([my.mean, mx.mean])) / np.concatenate([my.sd, mx.sd])
            v = np.column_stack([np.ones(len(v)), v])
            total += v.T @ v
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(size * size), pa.int32()), pa.array(total.ravel())], names=["at", "v"])

    rows = pairs.select(*(f"y_{a}" for a in attrs), *(f"x_{a}" for a in attrs)).mapInArrow(work, "at int, v double").groupBy("at").agg(F.sum("v").alias("v")).collect()
    g = np.zeros((2 * n + 1) ** 2)
    for r in rows:
        g[r["at"]] = r["v"]
    g = g.reshape(2 * n + 1, 2 * n + 1)
    if g[0, 0] < 2:
        return np.eye(n), np.zeros(n)
    if solver == "lstsq":
        w = np.linalg.lstsq(g[: n + 1, : n + 1], g[: n + 1, n + 1 :], rcond=None)[0]
        return w[1:].T, w[0]
    if solver != "procrustes":
        raise ValueError(f"solver is lstsq or procrustes, not {solver}")
    my_, mx_ = g[0, 1 : n + 1] / g[0, 0], g[0, n + 1 :] / g[0, 0]
    cross = g[n + 1 :, 1 : n + 1] - g[0, 0] * np.outer(mx_, my_)
    u, _, v = np.linalg.svd(cross)
    a = u @ v
    return a, mx_ - a @ my_


def known_io(orig: DataFrame, released: DataFrame, attrs: list[str], frac: float = 0.1, solver: str = "lstsq", seed: str = "io", pairing: str = "true", scale: str = "both", pairs: DataFrame | None = None, sides: tuple[Moments, Moments] | None = None) -> DataFrame:
    """Known input and output: a keyed share of pairs gives a linear map that undoes the rest."""
    pairs = pairs or pair(orig, released, attrs, pairing)
    mx, my = sides or (fit(orig, attrs), fit(released, attrs))
    a, b = known_io_fit(pairs.where(uniform(seed, "known", F.col(KEY)) < frac), attrs, mx, my, solver)
    undone = Moments(my.attrs, my.rows, b, np.sqrt(np.einsum("ij,jk,ik->i", a, my.cov, a)), my.cov)
    return resistance(_mapped(pairs, attrs, my, a, b), attrs, scale, (mx, undone) if sides else None)


def _mapped(pairs: DataFrame, attrs: list[str], my: Moments, a: np.ndarray, b: np.ndarray) -> DataFrame:
    return linear(pairs, [f"y_{x}" for x in attrs], a / my.sd, b - (a / my.sd) @ my.mean)


def whitening(m: Moments) -> np.ndarray:
    values, vectors = np.linalg.eigh(m.cov)
    return (vectors / np.sqrt(np.maximum(values, 1e-12))).T


def ica_fit(released: DataFrame, attrs: list[str], fn: str = "logcosh", iters: int = 100, tol: float = 1e-5, seed: str = "ica") -> tuple[np.ndarray, Moments]:
    """Rows that unmix the standardized release into independent components (symmetric fixed point).

    Every step is one pass that adds up n * n numbers over partitions."""
    m = fit(released, attrs)
    white, n = whitening(m), len(attrs)
    rows = linear(released.select(*attrs), attrs, white / m.sd, -(white / m.sd) @ m.mean).persist()

    def step(w: np.ndarray) -> np.ndarray:
        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            outer, slope, count = np.zeros((n, n)), np.zeros(n), 0
            for batch in batches:
                z = np.column_stack([batch.column(i).to_numpy(zero_copy_only=False) for i in range(n)])
                y = z @ w.T
                g = np.tanh(y) if fn == "logcosh" else y * np.exp(-y * y / 2) if fn == "exp" else y**3
                d = 1 - g * g if fn == "logcosh" else (1 - y * y) * np.exp(-y * y / 2) if fn == "exp" else 3 * y * y
                outer, slope, count = outer + g.T @ z, slope + d.sum(axis=0), count + len(z)
            flat = np.concatenate([[count], slope, outer.ravel()])
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat)), pa.int32()), pa.array(flat)], names=["at", "v"])

        flat = np.zeros(1 + n + n * n)
        for r in rows.mapInArrow(work, "at int, v double").groupBy("at").agg(F.sum("v").alias("v")).collect():
            flat[r["at"]] = r["v"]
        moved = flat[n + 1 :].reshape(n, n) / flat[0] - (flat[1 : n + 1] / flat[0])[:, None] * w
        u, _, v = np.linalg.svd(moved)
        return u @ v

    try:
        w = np.linalg.qr(gaussian_matrix(seed, "start", n, n))[0]
        for _ in range(iters):
            now = step(w)
            settled = np.abs(np.abs((now * w).sum(axis=1)) - 1).max() < tol
            w = now
            if settled:
                break
    finally:
        rows.unpersist()
    return w @ white, m


def match_components(corr: np.ndarray) -> list[tuple[int, int, float]]:
    """Pairs every attribute (row) with a component (column), strongest correlation first: (attribute, component, sign)."""
    left, out = np.abs(corr), []
    left = left.copy()
    for _ in range(len(corr)):
        i, j = np.unravel_index(int(left.argmax()), left.shape)
        out.append((int(i), int(j), float(np.sign(corr[i, j]) or 1)))
        left[i, :] = left[:, j] = -1
    return sorted(out)


def ica(orig: DataFrame, released: DataFrame, attrs: list[str], pairing: str = "true", scale: str = "both", pairs: DataFrame | None = None, sides: tuple[Moments, Moments] | None = None, **how) -> DataFrame:
    """Independent components of the release, matched to the attributes by the evaluator, who knows the original."""
    unmix, my = ica_fit(released, attrs, **how)
    pairs = _mapped(pairs or pair(orig, released, attrs, pairing), attrs, my, unmix, np.zeros(len(attrs))).persist()
    try:
        both = fit(pairs, [*(f"x_{a}" for a in attrs), *(f"y_{a}" for a in attrs)], method="gram")
        n = len(attrs)
        matched = match_components(both.cov[:n, n:])
        turned = pairs.select(KEY, *(f"x_{a}" for a in attrs), *((F.col(f"y_{attrs[j]}") * sign).alias(f"y_{attrs[i]}") for i, j, sign in matched))
        return resistance(turned, attrs, scale)
    finally:
        pairs.unpersist()


def known_sample(orig: DataFrame, released: DataFrame, attrs: list[str], frac: float = 0.1, seed: str = "sample", pairing: str = "true") -> DataFrame:
    """A sample of like records without pairing: its principal axes are laid over the release's."""
    ms, my = fit(orig.where(uniform(seed, "known", F.col(KEY)) < frac), attrs), fit(released, attrs)
    vs, vy = np.linalg.eigh(ms.cov)[1], np.linalg.eigh(my.cov)[1]
    vs, vy = vs * np.sign(vs.sum(axis=0)), vy * np.sign(vy.sum(axis=0))
    return resistance(_mapped(pair(orig, released, attrs, pairing), attrs, my, vs @ vy.T, np.zeros(len(attrs))), attrs)


def eigen(orig: DataFrame, released: DataFrame, attrs: list[str]) -> list[tuple[int, float, float]]:
    """Eigenvalues of the two correlation matrices side by side."""
    a, b = (np.linalg.eigvalsh(fit(x, attrs).cov)[::-1] for x in (orig, released))
    return [(i + 1, float(x), float(y)) for i, (x, y) in enumerate(zip(a, b, strict=True))]


def complementary(orig: DataFrame, releases: list[DataFrame], attrs: list[str]) -> DataFrame:
    """Several releases, linked by the hidden key and averaged, taken for the original."""
    rows = releases[0].select(KEY, *attrs)
    for other in releases[1:]:
        rows = rows.unionByName(other.select(KEY, *attrs))
    return naive(orig, rows.groupBy(KEY).agg(*(F.avg(a).alias(a) for a in attrs)), attrs)


def distance(orig: DataFrame, released: DataFrame, attrs: list[str], known: int = 30, eps: float = 0.05, seed: str = "dist", moments: Moments | None = None) -> DataFrame:
    """Known records' pair distances sought in the release: pairs, matches, and how many are true.

    The attacker knows `known` records (a keyed draw) and, at worst, where one record of a pair went. All released
    rows are candidates for the other: a match lies as far from the first, up to eps, as the two known records do.
    Distances are of values standardized by each side's own moments (moments: the original's, where they are known);
    `known` times the rows are compared, on Arrow batches. Only the known records reach the driver."""
    mine = [r[0] for r in orig.select(KEY).orderBy(uniform(seed, "known", F.col(KEY)), KEY).limit(known).collect()]
    n, mx, my = len(attrs), moments or fit(orig, attrs), fit(released, attrs)

    def own(df: DataFrame, m: Moments) -> list[tuple[str, np.ndarray]]:
        return [(r[0], (np.array(r[1:]) - m.mean) / m.sd) for r in df.where(F.col(KEY).isin(mine)).select(KEY, *attrs).collect()]

    def gap(at: np.ndarray, other: list) -> np.ndarray:
        return np.sqrt(sum(((at[i] - other[i]) ** 2 for i in range(n)), np.float64(0.0)))

    x, y = own(orig, mx), own(released, my)
    pairs = [(k1, k2, float(gap(p, q))) for k1, p in x for k2, q in x if k1 < k2]
    sought = [(k, at, of) for k, at in y if (of := [(k2, d) for k1, k2, d in pairs if k1 == k])]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matches = true_matches = 0
        for batch in batches:
            keys = batch.column(0)
            known_at = np.asarray(pc.is_in(keys, pa.array(mine, keys.type)), dtype=bool)
            known_rows = [(int(i), keys[int(i)].as_py()) for i in np.flatnonzero(known_at)]
            z = [(batch.column(1 + i).to_numpy(zero_copy_only=False) - my.mean[i]) / my.sd[i] for i in range(n)]
            for first, at, of in sought:
                e = gap(at, z)
                for i, key in known_rows:
                    if key == first:
                        e[i] = np.nan
                    else:
                        true_matches += sum(key == k2 and bool(abs(d - e[i]) < eps) for k2, d in of)
                matches += sum(int(np.count_nonzero(np.abs(d - e) < eps)) for _, d in of)
        yield pa.RecordBatch.from_arrays([pa.array([matches]), pa.array([true_matches])], names=["matches", "true_matches"])

    found = released.select(KEY, *attrs).mapInArrow(work, "matches long, true_matches long")
    return found.agg(F.lit(len(pairs)).cast("long").alias("pairs"), *(F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("matches", "true_matches")))


def risk_table(measured: DataFrame) -> DataFrame:
    """From attack and std_min (null: not conclusive) a level: at 0.5 or more low, 0.2 or more moderate, else high."""
    level = F.when(F.col("std_min").isNull(), "inconclusive").when(F.col("std_min") >= 0.5, "low").when(F.col("std_min") >= 0.2, "moderate").otherwise("high")
    return measured.select("attack", "std_min", level.alias("level"))
