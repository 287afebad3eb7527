"""Cost and accuracy measures of estimates against a truth."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nodeflux.functions.params import Params, cost_bound, hop_cap, increment_bound, theta_for

from .graph import Graph
from .push import next_residue, sized


def relative_error(estimates: DataFrame, truth: DataFrame) -> DataFrame:
    """estimates(t, pagerank, ...) with `truth` and `rel`, from truth(node, pi)."""
    known = truth.select(F.col("node").alias("t"), F.col("pi").alias("truth"))
    return estimates.join(known, "t").withColumn("rel", F.abs(F.col("pagerank") - F.col("truth")) / F.col("truth"))


def error_report(errors: DataFrame, p: Params, keys: list[str]) -> DataFrame:
    """Mean and largest error over c, and the share of errors above c, by keys (subtotals by rollup)."""
    return errors.rollup(*keys).agg(
        F.avg(F.col("rel") / p.c).alias("mean_error_over_c"),
        F.max(F.col("rel") / p.c).alias("max_error_over_c"),
        F.avg((F.col("rel") > p.c).cast("double")).alias("failure_rate"),
        F.count("*").alias("queries"),
    )


def variance_ratio(g: Graph, estimates: DataFrame, truth: DataFrame, p: Params, hops: int | None = None) -> DataFrame:
    """(qid, t, variance, bound, ratio): variance over replicas and its bound, hops * theta * deg / n * pi."""
    cap = hop_cap(g.stats.n, p) if hops is None else hops
    spread = estimates.groupBy("qid", "t", "theta").agg(F.var_samp("pagerank").alias("variance"))
    known = spread.join(truth.select(F.col("node").alias("t"), "pi"), "t").join(g.nodes.select(F.col("node").alias("t"), "deg"), "t")
    bound = cap * F.col("theta") * F.col("deg") / g.stats.n * F.col("pi")
    return known.select("qid", "t", "variance", bound.alias("bound"), (F.col("variance") / bound).alias("ratio"))


def hop_variance(g: Graph, residue: DataFrame, p: Params, hop: int, reps: int, seed: int = 0, coin: str = "fast") -> DataFrame:
    """(qid, node, variance, bound): of what a node gets in one hop, the hop before held fixed; bound is theta times its mean."""
    copies = residue.drop("rep").withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))))
    got = next_residue(g, copies, p, hop, seed, "edge", coin).filter("node is not null")
    # a replica without a row got nothing
    sums = got.groupBy("qid", "node", "theta").agg(F.sum("r").alias("s"), F.sum(F.col("r") * F.col("r")).alias("ss"))
    mean = F.col("s") / reps
    return sums.select("qid", "node", ((F.col("ss") / reps - mean * mean) * reps / (reps - 1)).alias("variance"), (F.col("theta") * mean).alias("bound"))


def truncation_gap(truth: DataFrame, truncated: DataFrame) -> DataFrame:
    """(least, most): of the exact less the truncated PageRank; never below 0, at most c * alpha / 2n at the hop cap."""
    both = truth.select("node", F.col("pi").alias("full")).join(truncated.select("node", "pi"), "node", "full")
    gap = F.coalesce("full", F.lit(0.0)) - F.coalesce("pi", F.lit(0.0))
    return both.agg(F.min(gap).alias("least"), F.max(gap).alias("most"))


def reserve_gap(exact: DataFrame, state: DataFrame) -> DataFrame:
    """(qid, least, most): of the exact chance to end at t less the reserve; between 0 and eps."""
    both = exact.select("qid", "node", "value").join(state.select("qid", "node", "p"), ["qid", "node"], "full")
    gap = F.coalesce("value", F.lit(0.0)) - F.coalesce("p", F.lit(0.0))
    return both.groupBy("qid").agg(F.min(gap).alias("least"), F.max(gap).alias("most"))


def complexity_table(g: Graph, targets: DataFrame, p: Params) -> DataFrame:
    """(qid, t, deg, method, complexity, improvement): leading terms, and each over the main method's."""
    n, m, s = g.stats.n, g.stats.m, g.stats
    d = F.col("deg")
    ours = F.least(d.cast("double"), F.lit(math.sqrt(m)))
    sub = min((m**2 * s.max_deg / s.avg_deg**2) ** (1 / 3), (m**4 / s.avg_deg**3) ** (1 / 5))
    terms = [
        ("adaptive_push", ours), ("power_iteration", F.lit(float(m))), ("walk_sample", F.lit(float(n))),
        ("reverse_push", (n * d).cast("double")), ("reverse_push_priority", F.least((n * d).cast("double"), F.lit(float(m)))),
        ("blanket_bidirectional", F.sqrt(n * d)), ("residue_bidirectional", F.sqrt(n * d)),
        ("randomized_reverse_push", F.lit(float(n))), ("subgraph_walks", F.lit(sub)),
    ]
    rows = g.nodes.select(F.col("node").alias("t"), "deg").join(sized(targets.select("qid", "t")), "t")
    each = F.explode(F.array(*[F.struct(F.lit(k).alias("method"), v.alias("complexity")) for k, v in terms]))
    return rows.select("qid", "t", "deg", ours.alias("ours"), each.alias("x")).select(
        "qid", "t", "deg", "x.method", "x.complexity", (F.col("x.complexity") / F.col("ours")).alias("improvement")
    )


def bounds_table(g: Graph, targets: DataFrame, p: Params) -> DataFrame:
    """(qid, t, deg, theta, increment_bound, cost_bound)."""
    n, m = g.stats.n, g.stats.m
    rows = g.nodes.select(F.col("node").alias("t"), "deg").join(sized(targets.select("qid", "t")), "t")
    theta = theta_for(F.col("deg"), n, m, p)
    return rows.select("qid", "t", "deg", theta.alias("theta"), increment_bound(theta, p).alias("increment_bound"), cost_bound(F.col("deg"), n, m, p).alias("cost_bound"))


def tail_exponent(df: DataFrame, column: str, least: float) -> DataFrame:
    """(exponent, tail): power-law exponent of the values from `least` on, by the mean of their logs."""
    tail = df.filter(F.col(column) >= least)
    return tail.agg((1 + 1 / F.avg(F.log(F.col(column) / least))).alias("exponent"), F.count("*").alias("tail"))


def sweep_cut(g: Graph, vector: DataFrame) -> DataFrame:
    """(qid, size, volume, cut, conductance): the prefix of least conductance when nodes are ordered by value over degree."""
    from pyspark.sql import Window

    deg = g.nodes.select("node", "deg")
    score = F.round(F.col("value") / F.col("deg"), 12)
    ranked = vector.join(deg, "node").withColumn("rank", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc(score), "node")))
    place = ranked.select("qid", F.col("node").alias("dst"), F.col("rank").alias("other"))
    inside = (
        ranked.join(g.edges.select("src", "dst"), F.col("node") == F.col("src")).join(place, ["qid", "dst"])
        .filter("other < rank").groupBy("qid", "rank").agg((2 * F.count("*")).alias("closed"))
    )
    run = Window.partitionBy("qid").orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    grown = ranked.join(inside, ["qid", "rank"], "left").select(
        "qid", F.col("rank").alias("size"), F.sum("deg").over(run).alias("volume"),
        (F.sum("deg").over(run) - F.sum(F.coalesce("closed", F.lit(0))).over(run)).alias("cut"),
    )
    other = F.least("volume", 2 * g.stats.m - F.col("volume"))
    scored = grown.filter(other > 0).withColumn("conductance", F.col("cut") / other)
    return scored.groupBy("qid").agg(F.min(F.struct("conductance", "size", "volume", "cut")).alias("x")).select("qid", "x.size", "x.volume", "x.cut", "x.conductance")
