"""Column helpers that several operators share."""

from __future__ import annotations

import importlib

from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from nodeflux.plans.storage import cut, discard, shared_dir  # noqa: F401

WHITE = " \t\n\x0b\x0c\r"
WORD = r"[^\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ship(*modules: str) -> None:
    """Pickle the functions of these modules by value, so that workers need no install."""
    for name in modules:
        cloudpickle.register_pickle_by_value(importlib.import_module(name))


def lower_ascii(c: Column) -> Column:
    """A-Z to a-z and nothing else; pure ASCII strings take the JVM's fast path."""
    return F.when(F.octet_length(c) == F.char_length(c), F.lower(c)).otherwise(
        F.translate(c, UPPER, LOWER)
    )


def partitions(df: DataFrame) -> int:
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def row_id(c: Column) -> Column:
    """A 64-bit stand-in for an id of any type, null included; with the text's hash it names a row."""
    return F.xxhash64(c.isNull(), c.cast("string"))


def fresh_names(df: DataFrame, *names: str) -> list[str]:
    """The names, lengthened until no column of df (in any case of letters) has them."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name in taken:
            name += "_"
        taken.add(name)
        out.append(name)
    return out
