"""Aggregate functions for SQL users."""

from __future__ import annotations

import sys

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType


def _median_of_means(value: pd.Series, rep: pd.Series, groups: pd.Series) -> float:
    held = value.notna()
    if not held.any():
        return None
    return float(value[held].groupby(rep[held] % int(groups.iloc[0])).mean().median())


#: median_of_means(value, rep, groups): the median over `groups` groups of replicas of each group's mean; nulls are left out.
#: A group of rows is one key's replicas, whose number the caller chose.
median_of_means = F.pandas_udf(_median_of_means, DoubleType())


def register(spark: SparkSession) -> None:
    """median_of_means(value, rep, groups) for SQL."""
    from pyspark import cloudpickle

    cloudpickle.register_pickle_by_value(sys.modules[__name__])
    spark.udf.register("median_of_means", median_of_means)
