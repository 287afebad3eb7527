"""Sinks of estimates: tables by method that later runs append to and others read."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_estimates(estimates: DataFrame, path: str, run: str, fmt: str = "parquet") -> None:
    """Append estimates(method, ...) of a named run; a method's rows stand in a partition of their own."""
    estimates.withColumn("run", F.lit(run)).write.mode("append").format(fmt).partitionBy("method").save(path)


def read_estimates(spark: SparkSession, path: str, method: str | None = None, fmt: str = "parquet") -> DataFrame:
    """All runs, or those of one method, whose partition alone is read."""
    rows = spark.read.format(fmt).load(path)
    return rows if method is None else rows.filter(F.col("method") == method)
