"""Exact methods: power iteration, truncated PageRank, hop vectors, personalised vectors."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from nodeflux.functions.params import Params, hop_cap
from nodeflux.plans.iterate import repeat
from nodeflux.plans.storage import cut, discard

from . import blocks
from .graph import Graph


def power_step(g: Graph, pi: DataFrame, p: Params) -> DataFrame:
    """One application of the defining equation to pi(node, pi); a node without edges keeps 1 / n."""
    n = g.stats.n
    told = pi.join(g.edges.select("src", "dst", "src_deg"), F.col("node") == F.col("src")).select(
        F.col("dst").alias("node"), ((1 - p.alpha) * F.col("pi") / F.col("src_deg")).alias("pi")
    )
    base = g.nodes.select("node", F.when(F.col("deg") == 0, 1.0 / n).otherwise(p.alpha / n).alias("pi"))
    return told.union(base).groupBy("node").agg(F.sum("pi").alias("pi"))


def power_iteration(g: Graph, p: Params = Params(), max_iter: int = 100, tol: float | None = None) -> DataFrame:
    """(node, pi) of all nodes; tol stops when n times the largest change is below it."""
    n = g.stats.n
    pi = g.nodes.select("node", F.lit(1.0 / n).alias("pi"))
    if tol is None:
        return repeat(pi, lambda x, _: power_step(g, x, p), max_iter, name="power")
    pi = cut(pi, "power")
    for _ in range(max_iter):
        after = cut(power_step(g, pi, p), "power")
        change = after.join(pi.withColumnRenamed("pi", "was"), "node").agg(F.max(F.abs(F.col("pi") - F.col("was")))).first()[0]
        discard(pi)
        pi = after
        if change is None or change * n < tol:
            break
    return pi


def convergence(g: Graph, p: Params, iterations: int) -> DataFrame:
    """(iteration, change, ratio): largest change of each iteration and its ratio to the one before."""
    pi = cut(g.nodes.select("node", F.lit(1.0 / g.stats.n).alias("pi")), "power")
    rows, last = [], None
    for i in range(1, iterations + 1):
        after = cut(power_step(g, pi, p), "power")
        change = after.join(pi.withColumnRenamed("pi", "was"), "node").agg(F.max(F.abs(F.col("pi") - F.col("was")))).first()[0]
        rows.append((i, float(change), float(change / last) if last else None))
        last, pi = change, after
    return g.spark.createDataFrame(rows, "iteration int, change double, ratio double")


def push_all(vec: DataFrame, g: Graph, keys: list[str], decay: float) -> DataFrame:
    """One hop: each node pays all neighbours an equal part of decay * r."""
    return (
        vec.join(g.edges.select("src", "dst", "src_deg"), F.col("node") == F.col("src"))
        .groupBy(*keys, F.col("dst").alias("node")).agg(F.sum(decay * F.col("r") / F.col("src_deg")).alias("r"))
    )


def series(start: DataFrame, g: Graph, keys: list[str], decay: float, weights: list[float]) -> DataFrame:
    """(keys, node, value): the sum of weights[l] * r_l, r_0 = start(keys, node, r).

    Sum and residue travel in one table, so each hop is one join and one shuffle, used once.
    """
    def hop(state: DataFrame, i: int) -> DataFrame:
        held = state.select(*keys, "node", (F.col("value") + weights[i] * F.col("r")).alias("value"), F.lit(0.0).alias("r"))
        paid = (
            state.filter("r > 0").join(g.edges.select("src", "dst", "src_deg"), F.col("node") == F.col("src"))
            .select(*keys, F.col("dst").alias("node"), F.lit(0.0).alias("value"), (decay * F.col("r") / F.col("src_deg")).alias("r"))
        )
        return held.union(paid).groupBy(*keys, "node").agg(F.sum("value").alias("value"), F.sum("r").alias("r"))

    end = repeat(start.select(*keys, "node", F.lit(0.0).alias("value"), "r"), hop, len(weights) - 1, name="series")
    return end.select(*keys, "node", (F.col("value") + weights[-1] * F.col("r")).alias("value"))


def one_hot(targets: DataFrame) -> DataFrame:
    return targets.select("qid", F.col("t").alias("node"), F.lit(1.0).alias("r"))


def truncated_pagerank(g: Graph, p: Params = Params(), hops: int | None = None) -> DataFrame:
    """(node, pi): PageRank of walks of at most `hops` moves, for all nodes; hops are products of blocks."""
    hops = hop_cap(g.stats.n, p) if hops is None else hops
    start = g.nodes.select(F.lit(0).alias("slot"), "node", F.lit(1.0 / g.stats.n).alias("r"))
    state = blocks.series(g, start, 1, 1 - p.alpha, [p.alpha] * (hops + 1))
    return blocks.values(g, state, 1).select("node", F.col("value").alias("pi"))


def hop_ppr(g: Graph, targets: DataFrame, ell: int, p: Params = Params()) -> DataFrame:
    """(qid, node, value): chance to stop at node after exactly ell moves from t."""
    vec = repeat(one_hot(targets), lambda x, _: push_all(x, g, ["qid"], 1 - p.alpha), ell, name="hop-ppr")
    return vec.select("qid", "node", (p.alpha * F.col("r")).alias("value"))


def ppr_from(g: Graph, targets: DataFrame, p: Params = Params(), hops: int | None = None) -> DataFrame:
    """(qid, node, value): personalised PageRank of source t."""
    hops = hop_cap(g.stats.n, p) if hops is None else hops
    return series(one_hot(targets), g, ["qid"], 1 - p.alpha, [p.alpha] * (hops + 1))


def ppr_to(g: Graph, targets: DataFrame, p: Params = Params(), hops: int | None = None, vector: DataFrame | None = None) -> DataFrame:
    """(qid, node, value): chance that a walk from node stops at t, by reversibility of ppr_from(t)."""
    vector = ppr_from(g, targets, p, hops) if vector is None else vector
    deg = g.nodes.select("node", "deg")
    goal = targets.join(deg.withColumnRenamed("node", "t").withColumnRenamed("deg", "t_deg"), "t").select("qid", "t_deg")
    return vector.join(deg, "node").join(F.broadcast(goal), "qid").select("qid", "node", (F.col("value") * F.col("t_deg") / F.col("deg")).alias("value"))


def heat_kernel(g: Graph, targets: DataFrame, h: float = 2.0, hops: int = 10) -> DataFrame:
    """(qid, node, value): heat kernel vector, hops weighted by a Poisson law."""
    return series(one_hot(targets), g, ["qid"], 1.0, [math.exp(-h) * h**k / math.factorial(k) for k in range(hops + 1)])


def weighted_ppr(edges: DataFrame, targets: DataFrame, p: Params, hops: int) -> DataFrame:
    """ppr_from on edges(src, dst, weight): a node pays its neighbours in proportion to weight."""
    total = edges.groupBy("src").agg(F.sum("weight").alias("all"))
    share = cut(edges.join(total, "src").select("src", "dst", (F.col("all") / F.col("weight")).alias("src_deg")), "weighted")

    class _Edges:
        pass

    g = _Edges()
    g.edges = share
    return series(one_hot(targets), g, ["qid"], 1 - p.alpha, [p.alpha] * (hops + 1))


def recurrence_gap(g: Graph, pi: DataFrame, p: Params = Params()) -> DataFrame:
    """(gap): largest violation of the defining equation."""
    after = power_step(g, pi, p)
    return after.join(pi.withColumnRenamed("pi", "was"), "node").agg(F.max(F.abs(F.col("pi") - F.col("was"))).alias("gap"))


def reversibility_gap(g: Graph, vectors: DataFrame, targets: DataFrame) -> DataFrame:
    """(qid, other, gap): ppr(u, v) deg(u) - ppr(v, u) deg(v) for pairs of targets."""
    deg = g.nodes.select(F.col("node").alias("t"), "deg")
    t = F.broadcast(targets.join(deg, "t"))
    between = vectors.join(t.select(F.col("qid").alias("other"), F.col("t").alias("node"), F.col("deg").alias("node_deg")), "node")
    one = between.join(t.select("qid", "deg"), "qid").select("qid", "other", (F.col("value") * F.col("deg")).alias("flow"))
    two = one.select(F.col("other").alias("qid"), F.col("qid").alias("other"), F.col("flow").alias("back"))
    return one.join(two, ["qid", "other"]).filter("qid < other").select("qid", "other", F.abs(F.col("flow") - F.col("back")).alias("gap"))


def lower_bounds(g: Graph, p: Params = Params()) -> DataFrame:
    """(node, deg, by_teleport, by_degree, by_edges): bounds that n * PageRank never falls below."""
    m = g.stats.m
    deg: Column = F.col("deg")
    return g.nodes.select(
        "node", "deg", F.lit(p.alpha).alias("by_teleport"),
        (p.alpha * (1 + (1 - p.alpha) * deg * deg / (2 * m))).alias("by_degree"),
        (deg * p.alpha * math.sqrt(2 * (1 - p.alpha) / m)).alias("by_edges"),
    )
