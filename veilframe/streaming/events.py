"""Streams: releases under a frozen model, window moments, drift of the guarantee, and the usual operators.

Every function takes a batch or a streaming DataFrame, so that the batch result is the stream's twin.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans import geometry, search
from ..plans.perturb import PerturbationModel, release

EVENTS = "event_id long, user_id long, ts timestamp_ntz, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, per_trigger: int = 1) -> DataFrame:
    """A stream of parquet files with event time et."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger).parquet(folder).withColumn("et", F.col("ts").cast("timestamp"))


def with_time(df: DataFrame) -> DataFrame:
    return df.withColumn("et", F.col("ts").cast("timestamp"))


def write_stream(df: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None):
    """Runs a query over all that is there into a memory table; returns the finished query."""
    writer = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    q = writer.start()
    q.awaitTermination()
    return q


def write_batches(df: DataFrame, each: Callable[[DataFrame, int], None], checkpoint: str):
    q = df.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def transform(stream: DataFrame, model: PerturbationModel, kind: str = "keyed") -> DataFrame:
    """Releases records as they come: a stateless projection, the same on replay."""
    return release(stream, model, "none", kind)


def _window(kind: str) -> Column:
    if kind == "tumbling":
        return F.window("et", "1 day")
    if kind == "sliding":
        return F.window("et", "1 day", "6 hours")
    if kind == "session":
        return F.session_window("et", "2 hours")
    raise ValueError(f"kind is tumbling, sliding or session, not {kind}")


def window_moments(stream: DataFrame, kind: str = "tumbling", late: str = "1 hour", by: tuple[str, ...] = ()) -> DataFrame:
    """Count, mean and deviation of value by window."""
    w = stream.withWatermark("et", late) if stream.isStreaming else stream
    out = w.groupBy(_window(kind).alias("w"), *by).agg(F.count(F.lit(1)).alias("n"), F.avg("value").alias("mean"), F.stddev_samp("value").alias("sd"))
    return out.select(F.col("w.start").cast("timestamp_ntz").alias("start"), F.col("w.end").cast("timestamp_ntz").alias("end"), *by, "n", "mean", "sd")


def phi_monitor(stream: DataFrame, model: PerturbationModel, tau: float = 0.2, late: str = "1 hour") -> DataFrame:
    """By day: the guarantee that the frozen parameters give that day's records, and whether it fell by over tau.

    The stream holds the model's attributes and et. Variances and covariances of a day are one aggregation."""
    attrs, n = list(model.attrs), len(model.attrs)
    if n > 8:
        raise ValueError("monitored attributes: up to eight")
    z = [(F.col(a) - m) / s for a, m, s in zip(attrs, model.mean, model.sd, strict=True)]
    a = geometry.rotation(n, model.theta) * geometry.reflection(n, model.axis, model.reflection)
    w = stream.withWatermark("et", late) if stream.isStreaming else stream
    gaps = [F.var_samp(sum((z[j] * float(a[i, j]) for j in range(n)), F.lit(0.0)) - z[i]) for i in range(n)]
    out = w.groupBy(F.window("et", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.array_min(F.array(*gaps)).alias("phi"))
    return out.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n", "phi", (F.col("phi") < (1 - tau) * model.phi_opt).alias("alert"))


def dedupe_stream(stream: DataFrame, key: str = "event_id", late: str = "1 hour") -> DataFrame:
    if stream.isStreaming:
        return stream.withWatermark("et", late).dropDuplicatesWithinWatermark([key])
    return stream.dropDuplicates([key])


def enrich(stream: DataFrame, static: DataFrame, on: str, right: str) -> DataFrame:
    return stream.join(static, F.col(on) == F.col(right), "left")


def pair_events(left: DataFrame, right: DataFrame, seconds: int = 3600, late: str = "1 hour") -> DataFrame:
    """Pairs of a user's events, the right one at most so many seconds after the left one; both sides watermarked."""
    a = left.select("event_id", "user_id", "et")
    b = right.select(F.col("event_id").alias("event_id_2"), F.col("user_id").alias("user_id_2"), F.col("et").alias("et_2"))
    if left.isStreaming:
        a, b = a.withWatermark("et", late), b.withWatermark("et_2", late)
    on = (F.col("user_id") == F.col("user_id_2")) & (F.col("et_2") > F.col("et")) & (F.col("et_2") <= F.col("et") + F.expr(f"INTERVAL {seconds} SECONDS"))
    return a.join(b, on).select("event_id", "event_id_2", "user_id")


def running_moments(stream: DataFrame) -> DataFrame:
    """Per event type the count, mean and deviation of all values so far, kept as state; update mode."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key: tuple, frames, state: GroupState):
        n, total, squares = state.get if state.exists else (0, 0.0, 0.0)
        for f in frames:
            v = f["value"].dropna().to_numpy()
            n, total, squares = n + len(v), total + float(v.sum()), squares + float((v * v).sum())
        state.update((n, total, squares))
        sd = float(np.sqrt(max(0.0, (squares - total * total / n) / (n - 1)))) if n > 1 else None
        yield pd.DataFrame([(key[0], n, total / n if n else None, sd)], columns=["event_type", "n", "mean", "sd"])

    return stream.groupBy("event_type").applyInPandasWithState(step, "event_type string, n long, mean double, sd double", "n long, total double, squares double", "update", GroupStateTimeout.NoTimeout)


def refit_every(k: int, fit: Callable[[DataFrame], PerturbationModel], keep: Callable[[PerturbationModel, int], None]) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: fits and keeps a new model version on every k-th micro-batch."""

    def each(batch: DataFrame, number: int) -> None:
        if number % k == 0 and not batch.isEmpty():
            keep(fit(batch), number)

    return each


def drift(cov: np.ndarray, model: PerturbationModel) -> float:
    """phi of the frozen parameters under another covariance."""
    n = len(model.attrs)
    return float(search.diff_variances(cov, geometry.rotation(n, model.theta) * geometry.reflection(n, model.axis, model.reflection)).min())
