"""Reading and writing tables."""

from __future__ import annotations

import contextlib

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, folder: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """A parquet table; the columns reach the scan, and so do filters put on the result."""
    df = spark.read.parquet(f"{folder}/{name}.parquet")
    return df.select(*columns) if columns else df


def read(spark: SparkSession, fmt: str, path: str, schema: str | None = None, **options) -> DataFrame:
    """csv, json, orc, text or parquet, under a given schema (never inferred)."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def read_jdbc(spark: SparkSession, url: str, table: str, column: str, lower: int, upper: int, partitions: int, **properties) -> DataFrame:
    """A table behind JDBC, read in ranges of a numeric column."""
    return spark.read.format("jdbc").options(url=url, dbtable=table, partitionColumn=column, lowerBound=lower, upperBound=upper, numPartitions=partitions, **properties).load()


def write_release(df: DataFrame, path: str | None = None, fmt: str = "parquet", partition_by: tuple[str, ...] = (), rows_per_file: int = 0, bucket: tuple[int, str] | None = None, table: str | None = None) -> None:
    """Writes a release: files, a bucketed table, or nowhere ("noop", for timing)."""
    writer = df.write.format(fmt).mode("overwrite")
    if rows_per_file:
        writer = writer.option("maxRecordsPerFile", rows_per_file)
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    if fmt == "csv":
        writer = writer.option("header", True)
    if bucket:
        if not table:
            raise ValueError("a bucketed release is a table")
        writer.bucketBy(*bucket).sortBy(bucket[1]).saveAsTable(table)
    elif fmt == "noop":
        writer.save()
    else:
        writer.save(path)


def replicate(df: DataFrame, times: int, key: str | None = None) -> DataFrame:
    """Every row so many times, with a column replica (and the key made unique by it)."""
    copies = df.sparkSession.range(times).select(F.col("id").cast("int").alias("replica"))
    out = df.crossJoin(F.broadcast(copies))
    return out.withColumn(key, F.concat_ws(":", F.col(key).cast("string"), F.col("replica").cast("string"))) if key else out


@contextlib.contextmanager
def as_view(df: DataFrame, name: str):
    """A temporary view for the time of a with block."""
    df.createOrReplaceTempView(name)
    try:
        yield name
    finally:
        df.sparkSession.catalog.dropTempView(name)
