"""Random walks as a table: one step is a join on (node, place in its list)."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nodeflux.functions.params import Params, walk_count
from nodeflux.plans.storage import cut

from .graph import Graph
from .push import edge_coin


def start_walks(g: Graph, n_walks: int, seed: int, coin: str = "fast") -> DataFrame:
    """(wid, node, deg) at uniform nodes; ids are dense, so a node is drawn by arithmetic."""
    u = edge_coin(coin, F.lit(seed), F.lit(-1), F.col("id"))
    drawn = g.spark.range(n_walks).select(F.col("id").alias("wid"), F.least(F.floor(u * g.stats.n), F.lit(g.stats.n - 1)).cast("long").alias("node"))
    return drawn.join(g.nodes.select("node", "deg"), "node").select("wid", "node", "deg")


def step_walks(g: Graph, alive: DataFrame, step: int, p: Params, seed: int, coin: str, keys: list[str]) -> tuple[DataFrame, DataFrame]:
    """(walks that stop here, walks after their move): rows (keys, node), the latter with deg, which the edges carry; a node without edges is left by none."""
    stop = (edge_coin(coin, F.lit(seed), F.lit(step), F.col("wid"), F.lit(0)) < p.alpha) | (F.col("deg") == 0)
    marked = alive.withColumn("stop", stop)
    place = F.least(F.floor(edge_coin(coin, F.lit(seed), F.lit(step), F.col("wid"), F.lit(1)) * F.col("deg")) + 1, F.col("deg")).cast("int")
    moving = marked.filter(~F.col("stop")).withColumn("place", place)
    lists = g.around(alive).select("src", "pos", "dst", "dst_deg")
    moved = moving.join(lists, (F.col("node") == F.col("src")) & (F.col("place") == F.col("pos")))
    return marked.filter("stop").select(*keys, "node"), moved.select(*keys, F.col("dst").alias("node"), F.col("dst_deg").alias("deg"))


def walk_visits(g: Graph, n_walks: int, p: Params, cap: int | None, seed: int, coin: str = "fast") -> DataFrame:
    """(step, wid, node, deg): every node that each walk meets, its start included, up to `cap` moves or to its end."""
    alive = cut(start_walks(g, n_walks, seed, coin), "walks")
    visits = alive.select(F.lit(0).alias("step"), "wid", "node", "deg")
    for step in count() if cap is None else range(cap):
        alive = cut(step_walks(g, alive, step, p, seed, coin, ["wid"])[1], "walks")
        if alive.isEmpty():
            break
        visits = visits.union(alive.select(F.lit(step + 1).alias("step"), "wid", "node", "deg"))
    return visits


def walk_ends(g: Graph, n_walks: int, p: Params, cap: int | None, seed: int, coin: str = "fast") -> DataFrame:
    """(step, wid, node): where each walk stopped; walks alive after `cap` moves are left out, without a cap none is."""
    visits = walk_visits(g, n_walks, p, cap, seed, coin)
    stop = (edge_coin(coin, F.lit(seed), F.col("step"), F.col("wid"), F.lit(0)) < p.alpha) | (F.col("deg") == 0)
    return visits.filter(stop).select("step", "wid", "node")


def walk_sample(g: Graph, targets: DataFrame, p: Params = Params(), n_walks: int | None = None, pi_hint: float | None = None, cap: int | None = None, seed: int = 0, coin: str = "fast") -> DataFrame:
    """(qid, t, pagerank, walks, method): share of walks that stop at t; one population serves all targets."""
    n_walks = walk_count(p, p.alpha / g.stats.n if pi_hint is None else pi_hint) if n_walks is None else n_walks
    ends = walk_ends(g, n_walks, p, cap, seed, coin).groupBy("node").agg(F.count("*").alias("held"))
    return targets.select("qid", "t").join(ends, F.col("t") == F.col("node"), "left").select(
        "qid", "t", (F.coalesce("held", F.lit(0)) / n_walks).alias("pagerank"), F.lit(n_walks).alias("walks"), F.lit("walk_sample").alias("method")
    )


def walk_length_stats(ends: DataFrame, p: Params) -> DataFrame:
    """(walks, mean_moves, expected): moves of ended walks against (1 - alpha) / alpha."""
    return ends.agg(F.count("*").alias("walks"), F.avg("step").alias("mean_moves"), F.lit((1 - p.alpha) / p.alpha).alias("expected"))
