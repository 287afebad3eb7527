"""Reading tables, edge lists and graphs; writing estimates."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, "
    "l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp",
    "events": "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "labels": "doc_id bigint, quality int, toxic int",
    "pages": "page_id bigint, url string, html string",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
    "benchmark": "item_id bigint, text string",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table; the footer gives the schema, so times keep the type they were written with."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edges(spark: SparkSession, fmt: str, path: str, a: str, b: str, **options: str) -> DataFrame:
    """Raw edges (a, b) from parquet, csv, json, orc, or text lines of two words."""
    if fmt == "text":
        pair = F.split(F.trim("value"), r"\s+")
        return spark.read.text(path).select(pair[0].alias("a"), pair[1].alias("b"))
    reader = spark.read.format(fmt).options(**options)
    if fmt in ("csv", "json") and "schema" not in options:
        reader = reader.schema(f"`{a}` string, `{b}` string") if fmt == "json" else reader
    return reader.load(path).select(F.col(a).cast("string").alias("a"), F.col(b).cast("string").alias("b"))


def from_query(spark: SparkSession, sql: str, a: str, b: str, **tables: DataFrame) -> DataFrame:
    """Raw edges from SQL; tables are named in braces."""
    return spark.sql(sql, **tables).select(F.col(a).cast("string").alias("a"), F.col(b).cast("string").alias("b"))


def write_estimates(df: DataFrame, fmt: str, path: str, mode: str = "error") -> None:
    flat = [F.to_json(c).alias(c) if kind.startswith(("array", "struct", "map")) else F.col(c) for c, kind in df.dtypes]
    (df.select(*flat) if fmt == "csv" else df).write.format(fmt).mode(mode).option("header", True).save(path)
