"""The experiments: query sets, methods and sweeps over graphs, with costs and errors."""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nodeflux.functions.params import Params
from nodeflux.plans.storage import cut, release

from . import bidirectional, resident
from .accuracy import relative_error
from .exact import power_iteration
from .graph import Graph, graph
from .push import adaptive_push
from .reverse import mean_reserve, randomized_reverse_push, reverse_push
from .targets import degree_targets, stratified_targets, uniform_targets
from .walks import walk_sample

METHODS = ("adaptive_push", "power_iteration", "walk_sample", "reverse_push", "reverse_push_priority", "blanket_bidirectional", "residue_bidirectional", "randomized_reverse_push_shared", "subgraph_walks")


def jobs(targets: DataFrame, methods: tuple[str, ...], reps: int = 1) -> DataFrame:
    named = targets.select("qid", "t", F.explode(F.array(*[F.lit(m) for m in methods])).alias("method"))
    return named.withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))))


def truth(g: Graph, p: Params, iterations: int = 100) -> DataFrame:
    """(node, pi) by power iteration, in one task where the graph fits one."""
    if not resident.fits(g):
        return power_iteration(g, p, iterations)
    return resident.power_rows(g, p, iterations)


def run_query_set(spark: SparkSession, sf_dir: str, names: list[str], methods: tuple[str, ...], kind: str, p: Params, k: int = 10, reps: int = 1, seed: int = 0, **options) -> DataFrame:
    """Rows of every (graph, method, target): estimate, increments, seconds, error over c.

    A graph's answers are written before the next graph's begin, so the driver plans and runs one graph at a time; the truth of
    a resident graph is one task, which runs beside the answers.
    """
    draw = {"uniform": uniform_targets, "degree": degree_targets, "strata": lambda g, n, s: stratified_targets(g, n, s)}[kind]
    parts = []
    for name in names:
        g = graph(spark, sf_dir, name)
        targets = cut(draw(g, k, seed), "targets")
        with ThreadPoolExecutor(1) as beside:
            later = beside.submit(truth, g, p) if resident.fits(g) else None
            rows = cut(answers(g, targets.select("qid", "t"), methods, p, reps, seed, **options), "answers")
            known = truth(g, p) if later is None else later.result()
        release(spark)
        extra = targets.select("qid", "stratum") if kind == "strata" else targets.select("qid", F.lit(None).cast("string").alias("stratum"))
        deg = g.nodes.select(F.col("node").alias("t"), "deg")
        parts.append(relative_error(rows, known).join(extra, "qid").join(deg, "t").withColumn("graph", F.lit(name)))
    return reduce(DataFrame.unionByName, parts).withColumn("error_over_c", F.col("rel") / p.c)


def summary(rows: DataFrame) -> DataFrame:
    """(graph, stratum, method): means over a query set."""
    return rows.groupBy("graph", "stratum", "method").agg(
        F.avg("seconds").alias("mean_seconds"), F.avg("increments").alias("mean_increments"),
        F.avg("error_over_c").alias("mean_error_over_c"), F.max("error_over_c").alias("max_error_over_c"), F.count("*").alias("queries"),
    )


def method_by_graph(rows: DataFrame, methods: tuple[str, ...]) -> DataFrame:
    """One row a graph, one column of mean increments a method."""
    return rows.groupBy("graph").pivot("method", list(methods)).agg(F.round(F.avg("increments"), 3))


def cost_vs_degree(rows: DataFrame) -> DataFrame:
    """(graph, method, slope): growth of log increments with log degree."""
    return rows.filter("increments > 0").groupBy("graph", "method").agg(
        F.regr_slope(F.log("increments"), F.log("deg")).alias("slope"), F.count("*").alias("queries")
    )


def _distributed(g: Graph, targets: DataFrame, method: str, p: Params, rep: int, seed: int, options: dict) -> DataFrame:
    """(qid, t, pagerank, increments, perhaps theta, exact_increments, draws) of one replica by the distributed plans."""
    theta, hops, coin = options.get("theta"), options.get("hops"), options.get("coin", "fast")
    if method == "adaptive_push":
        return adaptive_push(g, targets, p, theta=theta, hops=hops, sampler=options.get("sampler", "skip"), seed=seed + rep, coin=coin).df
    if method == "power_iteration":
        steps = options.get("iterations", 100)
        pi = power_iteration(g, p, steps).select(F.col("node").alias("t"), F.col("pi").alias("pagerank"))
        return targets.join(pi, "t").withColumn("increments", F.lit(2 * g.stats.m * steps))
    if method.startswith("reverse_push"):
        order, batch = ("priority", 1024) if method.endswith("priority") else ("sync", 1)
        return mean_reserve(g, targets, reverse_push(g, targets, p, options.get("eps"), order=order, batch=batch), method)
    if method.startswith("randomized_reverse_push"):
        return randomized_reverse_push(g, targets, p, theta, method.rsplit("_", 1)[-1], hops, seed=seed + rep, coin=coin)
    if method == "walk_sample":
        return walk_sample(g, targets, p, options.get("n_walks"), seed=seed + rep).withColumnRenamed("walks", "increments")
    return getattr(bidirectional, method)(g, targets, p, seed=seed + rep)


def answers(g: Graph, targets: DataFrame, methods: tuple[str, ...], p: Params, reps: int = 1, seed: int = 0, **options) -> DataFrame:
    """resident.OUT rows: by the resident engine where the graph fits it, else by the distributed plans.

    There a method answers all targets at once: seconds are its time over the number of targets, and
    increments of shared walks count for each target. Replicas of sampled methods differ by their seed.
    """
    if resident.fits(g):
        return resident.resident(g, jobs(targets, methods, reps), p, seed=seed, **options)
    parts, asked = [], max(1, targets.count())
    for method in methods:
        for rep in range(reps):
            began = time.perf_counter()
            rows = _distributed(g, targets.select("qid", "t"), method, p, rep, seed, options)
            for name, kind in (("theta", "double"), ("exact_increments", "long"), ("draws", "long")):
                rows = rows if name in rows.columns else rows.withColumn(name, F.lit(0).cast(kind))
            held = cut(rows.select("qid", F.lit(rep).alias("rep"), "t", "pagerank", "theta", "increments", "exact_increments", "draws"), "answers")
            parts.append(held.withColumn("seconds", F.lit((time.perf_counter() - began) / asked)).withColumn("method", F.lit(method)))
    return reduce(DataFrame.unionByName, parts)


def watch_list(g: Graph, k: int, p: Params, pi: DataFrame | None = None) -> DataFrame:
    """(qid, t): the k nodes of largest PageRank, to be asked for again and again."""
    pi = truth(g, p) if pi is None else pi
    top = pi.orderBy(F.desc(F.round("pi", 12)), "node").limit(k)
    from pyspark.sql import Window

    return top.select((F.row_number().over(Window.orderBy(F.desc(F.round("pi", 12)), "node")) - 1).cast("int").alias("qid"), F.col("node").alias("t"))


def draw_contrast(g: Graph, targets: DataFrame, p: Params, theta: float, reps: int, hops: int, seed: int = 0, **options) -> DataFrame:
    """(qid, t, shared, apart): variance over replicas when a push shares one draw and when each neighbour has its own."""
    names = ("randomized_reverse_push_shared", "randomized_reverse_push_edge")
    rows = answers(g, targets, names, p, reps, seed, theta=theta, hops=hops, **options)
    return rows.groupBy("qid", "t").pivot("method", list(names)).agg(F.var_samp("pagerank")).toDF("qid", "t", "shared", "apart")


def sweep(g: Graph, targets: DataFrame, thetas: list[float], p: Params, reps: int, seed: int = 0, **options) -> DataFrame:
    """(theta, mean_increments, mean_error): the trade of cost for accuracy."""
    parts = []
    known = truth(g, p)
    for theta in thetas:
        rows = answers(g, targets, ("adaptive_push",), p, reps, seed, theta=theta, **options)
        parts.append(relative_error(rows, known).agg(F.lit(theta).alias("theta"), F.avg("increments").alias("mean_increments"), F.avg("rel").alias("mean_error")))
    return reduce(DataFrame.unionByName, parts)


def parameter_sweep(g: Graph, targets: DataFrame, grid: list[Params], seed: int = 0, **options) -> DataFrame:
    """(alpha, c, pf, mean_increments, mean_error_over_c)."""
    parts = []
    for p in grid:
        rows = relative_error(answers(g, targets, ("adaptive_push",), p, seed=seed, **options), truth(g, p))
        parts.append(rows.agg(F.lit(p.alpha).alias("alpha"), F.lit(p.c).alias("c"), F.lit(p.pf).alias("pf"), F.avg("increments").alias("mean_increments"), F.avg(F.col("rel") / p.c).alias("mean_error_over_c")))
    return reduce(DataFrame.unionByName, parts)
