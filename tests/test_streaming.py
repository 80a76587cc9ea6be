"""Streams against their batch twins."""

import pytest
from pyspark.sql import functions as F

from veilframe.plans.matrix import KEY, NumericMatrixSpec, as_matrix
from veilframe.plans.perturb import fit_model
from veilframe.streaming import events as S


@pytest.fixture(scope="module")
def parts(spark, sf_small, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("events"))
    spark.read.parquet(f"{sf_small}/events.parquet").repartitionByRange(3, "ts").sortWithinPartitions("ts").write.mode("overwrite").parquet(folder)
    return folder


def test_release_of_a_stream(spark, parts, sf_small):
    batch = S.with_time(spark.read.parquet(f"{sf_small}/events.parquet")).withColumn("h", F.hour("ts").cast("double"))
    spec = NumericMatrixSpec(("value", "h"), ("event_id",))
    model = fit_model(as_matrix(batch, spec), spec)
    live = S.read_events(spark, parts).withColumn("h", F.hour("ts").cast("double"))
    S.write_stream(S.transform(as_matrix(live, spec), model), "rel")
    pick = lambda df: sorted((r[KEY], round(r.value, 6), round(r.h, 6)) for r in df.collect())
    assert pick(spark.table("rel")) == pick(S.transform(as_matrix(batch, spec), model))


def test_windows(spark, parts, sf_small):
    batch = S.with_time(spark.read.parquet(f"{sf_small}/events.parquet"))
    S.write_stream(S.window_moments(S.read_events(spark, parts)), "days", "complete")
    pick = lambda df: sorted((r.start, r.n, round(r["mean"], 6)) for r in df.collect())
    assert pick(spark.table("days")) == pick(S.window_moments(batch))
    assert S.window_moments(batch, "sliding").count() > 0 and S.window_moments(batch, "session", by=("user_id",)).count() > 0
    with pytest.raises(ValueError):
        S.window_moments(batch, "hopping")


def test_state_and_dedup(spark, parts, sf_small):
    batch = spark.read.parquet(f"{sf_small}/events.parquet")
    S.write_stream(S.running_moments(S.read_events(spark, parts)), "running", "update")
    last = {}
    for r in spark.table("running").collect():
        if r.n >= last.get(r.event_type, (0,))[0]:
            last[r.event_type] = (r.n, round(r["mean"], 6))
    want = {r.event_type: (r.n, round(r["mean"], 6)) for r in batch.groupBy("event_type").agg(F.count("value").alias("n"), F.avg("value").alias("mean")).collect()}
    assert last == want
    S.write_stream(S.dedupe_stream(S.read_events(spark, parts).union(S.read_events(spark, parts)), late="40 days"), "once")
    assert spark.table("once").count() == batch.count()


def test_refit(spark, parts, tmp_path):
    kept = []
    spec = NumericMatrixSpec(("value", "h"), ("event_id",))
    live = S.read_events(spark, parts).withColumn("h", F.hour("ts").cast("double"))
    each = S.refit_every(2, lambda b: fit_model(as_matrix(b, spec), spec), lambda m, k: kept.append((k, m.theta)))
    S.write_batches(live, each, str(tmp_path / "c"))
    assert [k for k, _ in kept] == [0, 2]


def test_drift_alert(spark, sf_small):
    batch = S.with_time(spark.read.parquet(f"{sf_small}/events.parquet")).withColumn("h", F.hour("ts").cast("double"))
    spec = NumericMatrixSpec(("value", "h"), ("event_id",), None, ("et",))
    m = as_matrix(batch, spec)
    model = fit_model(m, spec)
    assert S.phi_monitor(m, model, 0.9).where("alert").count() == 0
    flat = m.withColumn("value", F.col("value") * 1e-6 + model.mean[0])
    assert S.phi_monitor(flat, model, 0.2).where("alert").count() > 0
