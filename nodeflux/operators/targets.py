"""Query sets: uniform, by degree, and by strata of degree."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from nodeflux.functions.rng import u01_md5

from .graph import Graph

STRATA = (("huge", 100.0), ("large", 10.0), ("above", 1.0), ("below", 0.1), ("small", 0.01))


def _numbered(rows: DataFrame) -> DataFrame:
    return rows.withColumn("qid", (F.row_number().over(Window.orderBy("u", "t")) - 1).cast("int")).drop("u")


def uniform_targets(g: Graph, k: int = 10, seed: int = 0) -> DataFrame:
    """(qid, t): k nodes, each as likely as any other."""
    drawn = g.nodes.select(F.col("node").alias("t"), u01_md5(F.lit(seed), F.lit("node"), F.col("node")).alias("u"))
    return _numbered(drawn.orderBy("u", "t").limit(k)).select("qid", "t")


def degree_targets(g: Graph, k: int = 10, seed: int = 0) -> DataFrame:
    """(qid, t): k different nodes drawn in proportion to degree, as senders of drawn edges."""
    u = u01_md5(F.lit(seed), F.lit("edge"), F.col("src"), F.col("dst"))
    drawn = g.pairs.select(F.col("src").alias("t"), u.alias("u"))
    # the least draw of a node's edges; equal nodes are drawn again, so the k least of these remain
    first = drawn.groupBy("t").agg(F.min("u").alias("u")).orderBy("u", "t").limit(k)
    return _numbered(first).select("qid", "t")


def stratum(avg: float):
    found = F.lit(None).cast("string")
    for name, low in reversed(STRATA):
        high = {"huge": float("inf"), "large": 100.0, "above": 10.0, "below": 1.0, "small": 0.1}[name]
        found = F.when((F.col("deg") >= low * avg) & (F.col("deg") < high * avg), name).otherwise(found)
    return found


def stratified_targets(g: Graph, k: int = 5, seed: int = 0) -> DataFrame:
    """(qid, t, stratum): k nodes for each of five ranges of degree over the mean, where there are any."""
    u = u01_md5(F.lit(seed), F.lit("stratum"), F.col("node"))
    rows = g.nodes.select(F.col("node").alias("t"), stratum(g.stats.avg_deg).alias("stratum"), u.alias("u")).filter("stratum is not null")
    taken = None
    for name, _ in STRATA:
        part = rows.filter(F.col("stratum") == name).orderBy("u", "t").limit(k)
        taken = part if taken is None else taken.union(part)
    return _numbered(taken).select("qid", "t", "stratum")
