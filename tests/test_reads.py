"""Queries whose tasks once read no table."""

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from veilframe.operators import joins

MOVED = ["box_stats_accuracy", "friedman_accuracy", "friedman_memory", "friedman_resistance", "refl_signs", "rot_matrix_n2", "rot_matrix_n3", "rot_matrix_n4", "sql_table_function"]


@pytest.mark.parametrize("name", MOVED)
def test_scans_the_table(spark, sf_small, name):
    df = entry.queries()[name](spark, sf_small)
    assert any(f.endswith("lineitem.parquet") for f in df.inputFiles())


def test_rotation_check_follows_the_records(spark, sf_small, sf_mid):
    a, b = ({r.theta_deg: r.greatest for r in entry.queries()["rot_orthogonal"](spark, d).collect()} for d in (sf_small, sf_mid))
    assert a.keys() == b.keys() and a != b


def test_search_takes_every_twentieth_row_against_all(spark):
    rows = spark.range(45).select("id", (F.col("id") * 1.5).alias("v"))
    got = {(r.k1, r.k2) for r in joins.search_rows(rows, "id", ["v"]).collect()}
    assert got == {(a, b) for a in (0, 20, 40) for b in range(45) if a != b}
