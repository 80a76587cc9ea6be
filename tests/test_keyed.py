"""Keyed draws on Arrow batches, and the scan, against their plain forms."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from veilframe.functions.rng import keyed_normals, normal, normal_of
from veilframe.plans import attacks, datasets, geometry, search


def test_batches_draw_as_the_driver_does():
    keys = ["", "7", "1:2:3:4", "é" * 5, "k" * 40, "k" * 45, "k" * 300, *(str(10**i) for i in range(12))]
    whole = pa.array(["skipped", *keys])
    for k in (pa.array(keys), whole.slice(1)):
        got = list(keyed_normals(k, "smp", "noise", 12))
        assert np.allclose(got, [[normal_of("smp", "noise", x, j) for x in keys] for j in range(12)], rtol=1e-12)
    assert len(list(keyed_normals(pa.array([], pa.string()), "s", "t", 2))) == 2
    long_seed = [normal_of("s" * 60, "t", x, 0) for x in keys]
    assert np.allclose(next(keyed_normals(pa.array(keys), "s" * 60, "t", 1)), long_seed, rtol=1e-12)


def test_null_keys_draw_as_spark_does(spark):
    df = spark.createDataFrame([("a",), (None,), ("b" * 70,)], "k string")
    want = [[r[j] for r in df.select(*(normal("s", "t", F.col("k"), j) for j in range(3))).collect()] for j in range(3)]
    assert np.allclose(list(keyed_normals(pa.array(["a", None, "b" * 70]), "s", "t", 3)), want, rtol=1e-12)


@pytest.mark.parametrize("reflection", ["single", "complement"])
def test_scan_by_angle_equals_the_loop(spark, reflection):
    rng = np.random.default_rng(1)
    df = spark.createDataFrame([tuple(map(float, x)) for x in rng.normal(size=(700, 3)) @ rng.normal(size=(3, 3))], "a double, b double, c double")
    how = (df, ["a", "b", "c"], geometry.translation(3), [20, 50, 170])
    assert np.allclose(search.grid_scan(*how, reflection=reflection), search.grid_scan(*how, strategy="loop", reflection=reflection), rtol=1e-9)


def test_distance_reads_held_rows_and_drops_them(spark, sf_small, monkeypatch):
    import __spark_entry__ as entry

    held = []
    real = attacks.distance
    monkeypatch.setattr(attacks, "distance", lambda m, rel, attrs, **how: held.extend([m.storageLevel, rel.storageLevel]) or real(m, rel, attrs, **how))
    got = entry.queries()["distance_li4"](spark, sf_small)
    assert all(x.useDisk for x in held) and got.count() == 1 and not spark.sparkContext._jsc.sc().getPersistentRDDs().size()


def test_characters_are_counted_on_bytes(spark):
    texts = ["a", "éa\u20acé b", "", "zzz", "\u4e2d\u6587 aB", "a" * 70_000, None, "éà"]
    docs = spark.createDataFrame([(i, t, "en", len(t or "")) for i, t in enumerate(texts)], "doc_id long, text string, lang string, n_chars long").coalesce(1)
    classes = {"a": "a", "accents": "éà", "wide": "\u20ac\u6587", "upper": "AB"}
    got = datasets.counted(docs, classes).orderBy("doc_id").collect()
    assert [tuple(r[c] for c in classes) for r in got] == [tuple(None if t is None else sum(t.count(x) for x in set(k)) for k in classes.values()) for t in texts]
    assert "translate" not in datasets.counted(docs, classes)._jdf.queryExecution().toString()


def test_time_sweep_builds_its_table_once(spark, sf_small, monkeypatch):
    from veilframe.plans import bench

    built, real = [], bench.as_matrix
    monkeypatch.setattr(bench, "as_matrix", lambda *a: built.append(a) or real(*a))
    got = bench.time_sweep(spark, sf_small, "li4", (0.5, 1.0), (3,), ("SMP-scan",))
    assert [(r[0], r[2]) for r in got] == [("SMP-scan", 4), ("SMP-scan", 4), ("SMP-scan", 3)] and got[0][1] < got[1][1] == got[2][1]
    assert len(built) == 1 and not spark.sparkContext._jsc.sc().getPersistentRDDs().size()
