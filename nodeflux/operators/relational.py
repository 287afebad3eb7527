"""Joins, windows and functions around the graphs that Spark has no single operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """left with the last `value` of right at or before each row's time, per key: one sort of the union, no pairs."""
    both = left.withColumn("__side", F.lit(1)).withColumn("__v", F.lit(None).cast(right.schema[value].dataType)).unionByName(
        right.select(key, at, F.lit(0).alias("__side"), F.col(value).alias("__v")), allowMissingColumns=True
    )
    upto = Window.partitionBy(key).orderBy(at, "__side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(f"last_{value}", F.last("__v", ignorenulls=True).over(upto)).filter("__side = 1").drop("__side", "__v")


def range_join(points: DataFrame, ranges: DataFrame, x: str, low: str, high: str, width: float) -> DataFrame:
    """points and the ranges [low, high) that hold them: an equi join on cells of `width`, then the exact test."""
    cells = ranges.withColumn("__cell", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    placed = points.withColumn("__cell", F.floor(F.col(x) / width))
    return placed.join(cells, "__cell").filter((F.col(x) >= F.col(low)) & (F.col(x) < F.col(high))).drop("__cell")


def sessions_of(events: DataFrame, key: str, at: str, gap_seconds: int) -> DataFrame:
    """(key, session, first, last, events): runs of rows with gaps of at most gap_seconds."""
    order = Window.partitionBy(key).orderBy(at)
    fresh = (F.unix_micros(F.col(at).cast("timestamp")) - F.unix_micros(F.lag(at).over(order).cast("timestamp"))) > gap_seconds * 1_000_000
    numbered = events.withColumn("session", F.sum(F.coalesce(fresh, F.lit(True)).cast("int")).over(order.rangeBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy(key, "session").agg(F.min(at).alias("first"), F.max(at).alias("last"), F.count("*").alias("events"))


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))
