"""One call for a batch of single-node queries: the engine is chosen by size and by expected cost."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nodeflux.functions.params import Params, cost_bound, hop_cap

from . import resident
from .exact import truncated_pagerank
from .graph import Graph
from .push import adaptive_push, sized
from .workloads import jobs

COLUMNS = ("qid", "t", "pagerank", "theta", "increments", "draws", "engine")


def choose_engine(g: Graph, targets: DataFrame, p: Params) -> str:
    """resident if the graph fits one task; else exact if the batch is expected to cost more than all nodes' exact values; else distributed."""
    if resident.fits(g):
        return "resident"
    n, m = g.stats.n, g.stats.m
    asked = g.nodes.select(F.col("node").alias("t"), "deg").join(sized(targets.select("t")), "t")
    expected = asked.agg(F.sum(cost_bound(F.col("deg"), n, m, p))).first()[0] or 0
    return "exact" if expected > 2.0 * m * hop_cap(n, p) else "distributed"


def single_node_pagerank(g: Graph, targets: DataFrame, p: Params = Params(), engine: str = "auto", seed: int = 0, theta: float | None = None) -> DataFrame:
    """COLUMNS for targets(qid, t); unknown targets give no row."""
    engine = choose_engine(g, targets, p) if engine == "auto" else engine
    if engine == "resident":
        rows = resident.resident(g, jobs(targets, ("adaptive_push",)), p, seed=seed, theta=theta)
    elif engine == "distributed":
        rows = adaptive_push(g, targets, p, theta=theta, seed=seed).df
    else:
        pi = truncated_pagerank(g, p).select(F.col("node").alias("t"), F.col("pi").alias("pagerank"))
        rows = targets.join(pi, "t").select("qid", "t", "pagerank", F.lit(0.0).alias("theta"), F.lit(2 * g.stats.m * hop_cap(g.stats.n, p)).cast("long").alias("increments"), F.lit(0).cast("long").alias("draws"))
    return rows.withColumn("engine", F.lit(engine)).select(*COLUMNS)
