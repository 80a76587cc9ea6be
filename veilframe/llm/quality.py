"""Quality rules: plain rules, then robust multivariate outliers among each language's and source's documents.

The statistics of every whole text become a transformed vector (VECTOR). For every language and source the
location and scatter of the vectors are estimated by minimum covariance determinant: concentration steps from
STARTS deterministic starts (median with quartile spreads, correlation of hyperbolic tangents, spatial signs),
each step keeping the h closest vectors of the group, until no determinant changes; of the starts the one with
the least determinant is taken. All rows take part in every step; a step is one aggregation of moments by
(group, start, distance bin), so that a group's size never matters to a task. Cuts between bins stand in for the
h-th distance, BINS_PER_OCTAVE bins to a doubling. A document is rejected if its Mahalanobis distance passes the
cut.

Most clean documents have no symbols, no repeated line and no repeated word, so the h closest vectors of a group
may lie on a plane, in which case the estimate has no scatter across it. Such a direction, and no other, takes its
scatter from the group's own rows off the plane: every statistic has a unit, the root mean square deviation of
those rows that differ from the group's median, and a direction with less than DEGENERATE of the variance that
the units give gets that variance.

Groups of fewer than `least` documents (ten to a dimension) take the estimate of their language, and languages
of fewer that of all documents.

A null text has no words and fails the plain rules. Null languages or sources are groups of their own.
Repeated rows are judged alike. An empty table gives no rows. Other columns, whatever their names, are not read.
"""

from __future__ import annotations

import functools
import itertools
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import drop_written, table, written

STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
#: Transformed statistics.
VECTOR = ("log_words", "word_length", "symbols", "dup_lines", "repeats")
STARTS, DEGENERATE = 3, 0.01
#: Standard deviation, in units, that keeps a step's scatter regular.
RIDGE = 1e-3
#: 0.999 quantile of chi-square with five degrees of freedom.
CHI2_CUT = 20.515
BINS_PER_OCTAVE, OCTAVES = 8, 40
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_SYMBOL = np.zeros(256, dtype=bool)
_SYMBOL[list(b"#*$%&|<>")] = True


def text_stats(raw: bytes) -> tuple[int, int, int, int, int]:
    """The five statistics of UTF-8 text. Words are runs of anything but 0x20 and 0x09 to 0x0D."""
    data = np.frombuffer(raw, np.uint8)
    words = raw.split()
    n = len(words)
    chars = int(np.count_nonzero((data & 0xC0) != 0x80)) - int(np.count_nonzero(_SPACE[data]))
    symbols = int(np.count_nonzero(_SYMBOL[data]))
    seen, dup = set(), 0
    for line in raw.split(b"\n"):
        if line in seen:
            dup += 1
        elif line.strip():  # with a word
            seen.add(line)
    repeated = 0
    if n >= 4:
        ids = np.fromiter(map(hash, words), np.int64, n).view(np.uint64)
        with np.errstate(over="ignore"):
            keys = ids[:-2] * np.uint64(0x9E3779B97F4A7C15) + ids[1:-1] * np.uint64(0xC2B2AE3D27D4EB4F) + ids[2:] * np.uint64(0x165667B19E3779F9)
        order = np.argsort(keys)
        same = keys[order[1:]] == keys[order[:-1]]
        if same.any():
            twice = np.zeros(len(keys), dtype=bool)
            twice[order[1:][same]] = True
            twice[order[:-1][same]] = True
            covered = np.zeros(n, dtype=bool)
            for i in range(3):
                covered[i : n - 2 + i] |= twice
            repeated = int(np.count_nonzero(covered))
    return n, chars, symbols, dup, repeated


def with_stats(docs: DataFrame) -> DataFrame:
    """doc_id, lang, source and the statistics of every whole text."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [text_stats((x.as_py() or "").encode("utf-8", "surrogatepass")) for x in batch.column(3)]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(3)), *(pa.array([r[i] for r in rows], pa.int64()) for i in range(5))], names=["doc_id", "lang", "source", *STATS])

    text = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("source").cast("string").alias("source"), F.col("text").cast("string").alias("text"))
    return text.mapInArrow(work, "doc_id long, lang string, source string, " + ", ".join(f"{s} long" for s in STATS))


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def vector_columns() -> dict[str, Column]:
    n = F.greatest(F.col("n_words"), F.lit(1)).cast("double")
    return {
        "log_words": F.log1p(F.col("n_words").cast("double")),
        "word_length": F.col("word_chars") / n,
        "symbols": F.sqrt(F.col("n_symbols") / n),
        "dup_lines": F.log1p(F.col("n_dup_lines").cast("double")),
        "repeats": F.sqrt(F.col("n_repeat_words") / n),
    }


def _pairs() -> list[tuple[int, int]]:
    return list(itertools.combinations_with_replacement(range(len(VECTOR)), 2))


def _bin(d2: Column) -> Column:
    """Logarithmic bins of a squared distance, the lowest for all below 2 ** -10."""
    top = BINS_PER_OCTAVE * OCTAVES
    return F.least(F.greatest(F.floor((F.log2(d2 + F.lit(2.0**-10)) + 10) * BINS_PER_OCTAVE), F.lit(0)), F.lit(top)).cast("int")


def _moments() -> list[Column]:
    sums = [F.sum(v).alias(f"s_{v}") for v in VECTOR]
    return [F.count(F.lit(1)).alias("n"), *sums, *(F.sum(F.col(VECTOR[i]) * F.col(VECTOR[j])).alias(f"q_{i}_{j}") for i, j in _pairs())]


@functools.cache
def _chi_square(p: int) -> tuple[np.ndarray, np.ndarray]:
    """On a grid, the mass of a chi-square law with p degrees of freedom, and its mean over that mass's part."""
    grid = np.linspace(0, 60, 60_001)[1:]
    density = grid ** (p / 2 - 1) * np.exp(-grid / 2)
    return np.cumsum(density) / density.sum(), np.cumsum(grid * density) / density.sum()


def consistency(share: float, p: int) -> float:
    """Factor that makes the scatter of the `share` closest normal vectors the scatter of all."""
    if share >= 1:
        return 1.0
    mass, first = _chi_square(p)
    last = int(np.searchsorted(mass, share, side="right")) - 1
    return share / max(1e-9, float(first[max(last, 0)]) / p)


def _regular(scatter: np.ndarray, unit: np.ndarray) -> tuple[np.ndarray, float]:
    """Scatter with a ridge of RIDGE units, and its log determinant in units."""
    whole = scatter + np.diag((RIDGE * unit) ** 2)
    return whole, float(np.linalg.slogdet(whole / np.outer(unit, unit))[1])


def final_scatter(scatter: np.ndarray, unit: np.ndarray) -> tuple[np.ndarray, int]:
    """Scatter with its degenerate directions given the units' variance, and how many these are."""
    values, turns = np.linalg.eigh(scatter / np.outer(unit, unit))
    flat = values < DEGENERATE
    return (turns * np.where(flat, 1.0, values)) @ turns.T * np.outer(unit, unit), int(flat.sum())


def concentrated(bins: np.ndarray, share: float) -> tuple[int, np.ndarray, np.ndarray]:
    """Size, location and scatter of the nearest `share` of one group. bins: rows of bin, count, sums and products."""
    bins = bins[np.argsort(bins[:, 0])]
    upto, p = np.cumsum(bins[:, 1]), len(VECTOR)
    total = int(upto[-1])
    last = int(np.searchsorted(upto, max(1, math.ceil(share * total))))
    n, sums = upto[last], bins[: last + 1, 2:].sum(axis=0) / upto[last]
    mean, scatter = sums[:p], np.zeros((p, p))
    for (i, j), q in zip(_pairs(), sums[p:], strict=True):
        scatter[i, j] = scatter[j, i] = q - mean[i] * mean[j]
    return total, mean, scatter * consistency(n / total, p)


GROUP = ("__level", "__lang", "__source")
MODEL = "__level string, __lang string, __source string, start int, size long, unit array<double>, mean array<double>, scatter array<double>, inverse array<double>, logdet double"


def _model_row(head: tuple, start: int, size: int, unit: np.ndarray, mean: np.ndarray, scatter: np.ndarray, first: bool = False) -> tuple:
    """first: a start, which any concentrated estimate replaces."""
    whole, logdet = _regular(scatter, unit)
    logdet = math.inf if first else logdet
    return (*head, start, size, unit.tolist(), mean.tolist(), scatter.ravel().tolist(), np.linalg.inv(whole).ravel().tolist(), logdet)


def _frame(rows: list[tuple], kinds: str = MODEL) -> pd.DataFrame:
    return pd.DataFrame(rows, columns=[x.split()[0] for x in kinds.split(", ")])


def _fit_groups(near: DataFrame, share: float) -> DataFrame:
    """A model row for each group and start. A group comes as the list of its moments by bin, of which there are few."""
    binned = near.groupBy(*GROUP, "start", "bin").agg(F.first("unit").alias("unit"), *_moments())
    moments = [c for c in binned.columns if c not in (*GROUP, "start", "unit")]
    lists = binned.groupBy(*GROUP, "start").agg(F.first("unit").alias("unit"), F.collect_list(F.array(*(F.col(c).cast("double") for c in moments))).alias("bins"))

    def fit(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            yield _frame([_model_row(head, start, size, np.array(unit), mean, scatter) for *head, start, unit, bins in f.itertuples(index=False) for size, mean, scatter in [concentrated(np.stack(bins), share)]])

    return lists.mapInPandas(fit, MODEL)


def start_estimates(spread: np.ndarray, tanh: np.ndarray, tanh_mean: np.ndarray, signs: np.ndarray) -> list[np.ndarray]:
    """The starts' scatters, from mean products of the tangents and of the spatial signs of (x - middle) / spread."""
    p = len(spread)
    cov = tanh - np.outer(tanh_mean, tanh_mean)
    sd = np.sqrt(np.maximum(np.diag(cov), 0.0))
    with np.errstate(invalid="ignore", divide="ignore"):
        corr = np.nan_to_num(cov / np.outer(sd, sd))
    np.fill_diagonal(corr, 1.0)
    return [m * np.outer(spread, spread) for m in (np.eye(p), corr, signs * p)]


def _starts(long: DataFrame) -> DataFrame:
    """MODEL rows of the starts of every group, in two aggregations."""
    p = len(VECTOR)
    quartiles = long.groupBy(*GROUP).agg(*(F.percentile_approx(v, F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75)), 2000).alias(f"m_{v}") for v in VECTOR), F.count(F.lit(1)).alias("size"))
    off = [F.when(F.col(v) != F.col(f"m_{v}")[1], F.pow(F.col(v) - F.col(f"m_{v}")[1], F.lit(2))) for v in VECTOR]
    units = _by_group(long, quartiles).groupBy(*GROUP).agg(*(F.sqrt(F.avg(x)).alias(f"u_{i}") for i, x in enumerate(off)))
    unit = F.array(*(F.coalesce(F.col(f"u_{i}"), F.lit(1.0)) for i in range(p)))
    model = quartiles.join(units.withColumnsRenamed({k: f"{k}_" for k in GROUP}), [F.col(k).eqNullSafe(F.col(f"{k}_")) for k in GROUP])
    model = model.select(*GROUP, "size", F.array(*(F.col(f"m_{v}")[1] for v in VECTOR)).alias("middle"), unit.alias("unit"), F.array(*(F.greatest((F.col(f"m_{v}")[2] - F.col(f"m_{v}")[0]) / 1.349, F.coalesce(F.col(f"u_{i}"), F.lit(1.0)) * 0.05) for i, v in enumerate(VECTOR))).alias("spread"))
    model = written(model, "mcd-start")
    z = _by_group(long, model).select(*GROUP, "size", "middle", "unit", "spread", *(((F.col(v) - F.col("middle")[i]) / F.col("spread")[i]).alias(f"z{i}") for i, v in enumerate(VECTOR)))
    norm = F.greatest(F.sqrt(sum((F.col(f"z{i}") * F.col(f"z{i}") for i in range(p)), F.lit(0.0))), F.lit(1e-9))
    z = z.select(*GROUP, "size", "middle", "unit", "spread", *(F.tanh(f"z{i}").alias(f"t{i}") for i in range(p)), *((F.col(f"z{i}") / norm).alias(f"w{i}") for i in range(p)))
    sums = z.groupBy(*GROUP, "size", "middle", "unit", "spread").agg(*(F.avg(f"t{i}").alias(f"t_{i}") for i in range(p)), *(F.avg(F.col(f"{k}{i}") * F.col(f"{k}{j}")).alias(f"{k}_{i}_{j}") for k in "tw" for i, j in _pairs()))

    def square(f: pd.DataFrame, k: str) -> np.ndarray:
        return np.stack([f[f"{k}_{min(i, j)}_{max(i, j)}"].to_numpy() for i in range(p) for j in range(p)], axis=1).reshape(-1, p, p)

    def begin(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            tanh, signs, means = square(f, "t"), square(f, "w"), f[[f"t_{i}" for i in range(p)]].to_numpy()
            rows = []
            for k, (*head, size, middle, unit, spread) in enumerate(f[[*GROUP, "size", "middle", "unit", "spread"]].itertuples(index=False)):
                scatters = start_estimates(np.array(spread), tanh[k], means[k], signs[k])
                rows += [_model_row(head, start, size, np.array(unit), np.array(middle), scatter, True) for start, scatter in enumerate(scatters)]
            yield _frame(rows)

    return sums.mapInPandas(begin, MODEL)


def _distance(mean: Column, inverse: Column) -> Column:
    p = len(VECTOR)
    gaps = [F.col(v) - mean[i] for i, v in enumerate(VECTOR)]
    out = F.lit(0.0)
    for i, j in _pairs():
        out = out + gaps[i] * gaps[j] * inverse[i * p + j] * (1.0 if i == j else 2.0)
    return F.greatest(out, F.lit(0.0))


def _levels(rows: DataFrame) -> DataFrame:
    """Each row once for its language and source, once for its language, once for all."""
    levels = F.array(
        F.struct(F.lit("pair").alias("level"), F.col("lang").alias("lang"), F.col("source").alias("source")),
        F.struct(F.lit("lang").alias("level"), F.col("lang").alias("lang"), F.lit(None).cast("string").alias("source")),
        F.struct(F.lit("all").alias("level"), F.lit(None).cast("string").alias("lang"), F.lit(None).cast("string").alias("source")),
    )
    return rows.withColumn("__g", F.explode(levels)).select("*", F.col("__g.level").alias("__level"), F.col("__g.lang").alias("__lang"), F.col("__g.source").alias("__source")).drop("__g")


def _by_group(rows: DataFrame, model: DataFrame, broadcast_groups: int = 50_000) -> DataFrame:
    """rows with their group's model columns. A group has under 2,000 bytes: broadcast while there are few groups,
    else joined by group."""
    right = model.withColumnsRenamed({k: f"{k}_" for k in GROUP})
    few = model.count() <= broadcast_groups
    on = (F.col("__level") == F.col("__level_")) & F.col("__lang").eqNullSafe(F.col("__lang_")) & F.col("__source").eqNullSafe(F.col("__source_"))
    return rows.join(F.broadcast(right) if few else right, on).drop(*(f"{k}_" for k in GROUP))


def mcd_models(rows: DataFrame, share: float = 0.75, steps: int = 12, settled: float = 1e-3) -> DataFrame:
    """MODEL rows of least determinant by level, degenerate directions filled, and their number `degenerate`.

    rows: lang, source and VECTOR, already written. Steps end when no log determinant falls by over `settled`."""
    long = _levels(rows)
    keys = [*GROUP, "start"]
    model = written(_starts(long), "mcd").withColumn("fell", F.lit(True))
    for _ in range(steps):
        # a step that does not lower the determinant is not taken: between bins, steps can go to and fro
        near = _by_group(long, model.select(*keys, "unit", "mean", "inverse")).withColumn("bin", _bin(_distance(F.col("mean"), F.col("inverse"))))
        both = _fit_groups(near, share).withColumn("step", F.lit(1)).unionByName(model.drop("fell").withColumn("step", F.lit(0)))
        columns = [c for c in model.columns if c not in (*keys, "fell")]
        least = both.groupBy(*keys).agg(F.min_by(F.struct(*columns), F.struct("logdet", "step")).alias("m"), (F.max(F.when(F.col("step") == 0, F.col("logdet"))) - F.min("logdet") > settled).alias("fell"))
        later = written(least.select(*keys, *(f"m.{c}" for c in columns), "fell"), "mcd")
        drop_written(model)
        model = later
        if not model.where("fell").limit(1).count():
            break
    best = model.groupBy(*GROUP).agg(F.min_by(F.struct("start", "size", "unit", "mean", "scatter", "logdet"), F.struct("logdet", "start")).alias("best")).select(*GROUP, "best.*")

    def finish(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        p = len(VECTOR)
        for f in frames:
            filled = [final_scatter(np.array(s).reshape(p, p), np.array(u)) for s, u in zip(f["scatter"], f["unit"], strict=True)]
            yield f.assign(inverse=[np.linalg.inv(s).ravel().tolist() for s, _ in filled], degenerate=[d for _, d in filled])[[*GROUP, "start", "size", "unit", "mean", "scatter", "inverse", "logdet", "degenerate"]]

    return written(best.mapInPandas(finish, MODEL + ", degenerate int"), "mcd")


def judged(docs: DataFrame, share: float = 0.75, steps: int = 12, least: int = 10 * len(VECTOR), cut: float = CHI2_CUT) -> DataFrame:
    """doc_id, lang, source, statistics, base_failed, distance (squared) and kept.

    Documents that fail the plain rules take no part in the estimates."""
    rows = written(with_stats(docs).withColumns({"base_failed": base_failed()}).withColumns(vector_columns()), "stats")
    model = mcd_models(rows.where("not base_failed"), share, steps)
    fit = model.where(F.col("size") >= least).select("__level", "__lang", "__source", "mean", "inverse")
    whole = model.where("__level = 'all'").select(F.col("mean").alias("mean_all"), F.col("inverse").alias("inverse_all"))
    langs = fit.where("__level = 'lang'").select(F.col("__lang").alias("l2"), F.col("mean").alias("mean_lang"), F.col("inverse").alias("inverse_lang"))
    pairs = fit.where("__level = 'pair'").select(F.col("__lang").alias("l1"), F.col("__source").alias("s1"), "mean", "inverse")
    if model.count() <= 50_000:
        langs, pairs = F.broadcast(langs), F.broadcast(pairs)
    found = rows.join(pairs, F.col("lang").eqNullSafe(F.col("l1")) & F.col("source").eqNullSafe(F.col("s1")), "left").join(langs, F.col("lang").eqNullSafe(F.col("l2")), "left").join(F.broadcast(whole), F.lit(True), "left")
    mean = F.coalesce("mean", "mean_lang", "mean_all")
    inverse = F.coalesce("inverse", "inverse_lang", "inverse_all")
    out = found.withColumn("distance", _distance(mean, inverse))
    return out.select("doc_id", "lang", "source", *STATS, "base_failed", "distance", (~F.col("base_failed") & (F.coalesce("distance", F.lit(0.0)) <= cut)).alias("kept"))


def keep_good(docs: DataFrame) -> DataFrame:
    """docs without those rejected. Rows that share a doc_id go only if all of them are rejected."""
    verdicts = judged(docs).groupBy("doc_id").agg(F.bool_or("kept").alias("__kept"))
    gone = verdicts.where("not __kept").select(F.col("doc_id").alias("__gone"))
    return docs.join(gone, F.col("doc_id").cast("long").eqNullSafe(F.col("__gone")), "left_anti")


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged(table(spark, sf_dir, "documents")).select("doc_id", *STATS, "base_failed", "kept", "distance")


QUERIES = {"op7_quality_rules": op7_quality_rules}
ORACLES: dict[str, str] = {}
