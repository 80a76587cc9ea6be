"""Registers the engine's functions for SQL: scalar ones expand to built-in expressions, tables are UDTFs."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..plans import geometry, search


def register(spark: SparkSession) -> None:
    """vf_uniform, vf_normal, vf_expand (SQL functions), vf_matvec and vf_phi (pandas), angle_grid and phi_grid (table functions)."""
    u = "(CAST(conv(substr(md5(concat_ws(':', seed, stream, key, j)), 1, 12), 16, 10) AS BIGINT) + 0.5D) / 281474976710656D"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION vf_uniform(seed STRING, stream STRING, key STRING, j INT) RETURNS DOUBLE RETURN {u}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vf_normal(seed STRING, stream STRING, key STRING, j INT) RETURNS DOUBLE RETURN sqrt(-2 * ln(vf_uniform(seed, concat(stream, 'a'), key, j))) * cos(2 * pi() * vf_uniform(seed, concat(stream, 'b'), key, j))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vf_expand(x DOUBLE, noise DOUBLE) RETURNS DOUBLE RETURN x + signum(x) * abs(noise)")

    @F.pandas_udf("array<double>")
    def vf_matvec(vectors: pd.Series, matrix: pd.Series) -> pd.Series:
        """matrix (by rows) times vector."""
        return pd.Series([(np.asarray(m).reshape(-1, len(v)) @ np.asarray(v)).tolist() for v, m in zip(vectors, matrix, strict=True)])

    @F.pandas_udf("double")
    def vf_phi(gaps: pd.Series) -> float:
        """Least variance over the places of arrays of differences; gathers a group, so for groups of bounded size."""
        return float(np.var(np.stack(gaps.to_list()), axis=0, ddof=1).min())

    spark.udf.register("vf_matvec", vf_matvec)
    spark.udf.register("vf_phi", vf_phi)

    @F.udtf(returnType="axis int, theta_deg int")
    class AngleGrid:
        def eval(self, n: int, step: int):
            for axis, degrees in search.candidates(n, geometry.angles(step=step)):
                yield axis, int(degrees)

    @F.udtf(returnType="axis int, theta_deg int, phi double")
    class PhiGrid:
        def eval(self, cov: list, n: int):
            degrees = geometry.angles()
            grid = search.grid_cov(np.asarray(cov, dtype=float).reshape(n, n), degrees)
            for a in range(n):
                for k, d in enumerate(degrees):
                    yield a + 1, d, float(grid[a, k])

    spark.udtf.register("angle_grid", AngleGrid)
    spark.udtf.register("phi_grid", PhiGrid)
