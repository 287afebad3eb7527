"""Reverse pushes: from the target, with the receiver's degree dividing what it gets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from nodeflux.functions.params import Params, hop_cap, push_eps, shared_theta
from nodeflux.plans.storage import cut_counted, discard

from .graph import Graph
from .push import edge_coin, sized


def start_state(g: Graph, targets: DataFrame) -> DataFrame:
    """state(qid, node, p, r) with all residue at t, for targets in the graph that have edges."""
    there = g.nodes.filter("deg > 0").select(F.col("node").alias("t"))
    return there.join(sized(targets), "t").select(
        "qid", F.col("t").alias("node"), F.lit(0.0).alias("p"), F.lit(1.0).alias("r"), F.lit(0).cast("long").alias("touched")
    )


def push_round(g: Graph, state: DataFrame, active: Column, p: Params, keys: list[str]) -> DataFrame:
    """Active nodes keep alpha of their residue and pay the rest; touched counts increments."""
    marked = state.withColumn("go", active)
    stay = marked.select(
        *keys, "node", F.when(F.col("go"), F.col("p") + p.alpha * F.col("r")).otherwise(F.col("p")).alias("p"),
        F.when(F.col("go"), 0.0).otherwise(F.col("r")).alias("r"), "touched",
    )
    pay = (
        marked.filter("go").join(g.around(marked.filter("go")).select("src", "dst", "dst_deg"), F.col("node") == F.col("src"))
        .select(*keys, F.col("dst").alias("node"), F.lit(0.0).alias("p"),
                ((1 - p.alpha) * F.col("r") / F.col("dst_deg")).alias("r"), F.lit(1).cast("long").alias("touched"))
    )
    return stay.union(pay).groupBy(*keys, "node").agg(F.sum("p").alias("p"), F.sum("r").alias("r"), F.sum("touched").alias("touched"))


def reverse_push(
    g: Graph,
    targets: DataFrame,
    p: Params = Params(),
    eps: float | Column | None = None,
    order: str = "sync",
    batch: int = 1,
    rounds: int | None = None,
) -> DataFrame:
    """state(qid, node, p, r, touched) once no residue reaches eps (a number, or a column of targets).

    order "sync" pushes every active node in a round, "priority" the `batch` largest residues
    of each query; any order keeps the invariant. A round is one job: what is still active is
    counted while the state is written, and eps rides in its rows.
    """
    limit: Column = F.lit(push_eps(g.stats.n, p)) if eps is None else eps if isinstance(eps, Column) else F.lit(float(eps))
    limits = g.nodes.select(F.col("node").alias("t"), "deg").join(sized(targets), "t").select("qid", limit.alias("eps"))
    active, keys, done = F.col("r") >= F.col("eps"), ["qid", "eps"], 0
    live = [F.count_if(active).alias("live")]
    state, seen = cut_counted(start_state(g, targets).join(limits, "qid").select(*keys, "node", "p", "r", "touched"), "reverse", live)
    while seen["live"] and (rounds is None or done < rounds):
        marked, go = state, active
        if order == "priority":
            first = Window.partitionBy("qid").orderBy(F.desc("r"), "node")
            heads = state.filter(active).withColumn("nth", F.row_number().over(first)).filter(F.col("nth") <= batch).select("qid", "node", F.lit(True).alias("first"))
            marked, go = state.join(heads, ["qid", "node"], "left"), F.coalesce("first", F.lit(False))
        after, seen = cut_counted(push_round(g, marked, go, p, keys), "reverse", live)
        discard(state)
        state, done = after, done + 1
    return state.drop("eps")


def mean_reserve(g: Graph, targets: DataFrame, state: DataFrame, method: str) -> DataFrame:
    """(qid, t, pagerank, increments, method)."""
    n = g.stats.n
    sums = state.groupBy("qid").agg((F.sum("p") / n).alias("pagerank"), F.sum("touched").alias("increments"))
    return targets.select("qid", "t").join(sums, "qid").withColumn("method", F.lit(method))


def randomized_reverse_push(
    g: Graph,
    targets: DataFrame,
    p: Params = Params(),
    theta: float | None = None,
    draw: str = "shared",
    hops: int | None = None,
    seed: int = 0,
    reps: int = 1,
    coin: str = "fast",
    pi_hint: float | None = None,
) -> DataFrame:
    """(qid, rep, t, pagerank, increments, method): increments below theta are paid as theta or not at all.

    "shared" decides all neighbours of a push by one draw, "edge" each by its own. A hop is one job; rows without a node
    hold the queries' sums up to it.
    """
    n = g.stats.n
    hops = hop_cap(n, p) if hops is None else hops
    theta = shared_theta(n, p, pi_hint) if theta is None else theta
    nodes = [F.count("node").alias("nodes")]

    def sums(residue: DataFrame) -> DataFrame:
        part = F.when(F.col("node").isNull(), F.col("r")).otherwise(F.col("r") * p.alpha / n)
        return residue.groupBy("qid", "rep").agg(F.sum(part).alias("r"), F.sum("n_in").alias("n_in")).withColumn("node", F.lit(None).cast("long"))

    start = start_state(g, targets).select("qid", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))).alias("rep"), "node", "r", F.lit(0).cast("long").alias("n_in"))
    residue, counts = cut_counted(start, "shared-hop", nodes)
    for hop in range(hops):
        if not counts["nodes"]:
            break
        front = residue.filter("node is not null")
        inc = (1 - p.alpha) * F.col("r") / F.col("dst_deg")
        key = [F.lit(seed), F.col("qid"), F.col("rep"), F.lit(hop), F.col("src")] + ([F.col("dst")] if draw == "edge" else [])
        paid = (
            sized(front, counts["nodes"]).join(g.around(front).select("src", "dst", "dst_deg"), F.col("node") == F.col("src"))
            .withColumn("inc", inc).filter((F.col("inc") >= theta) | (F.col("inc") >= edge_coin(coin, *key) * theta))
            .groupBy("qid", "rep", F.col("dst").alias("node")).agg(F.sum(F.greatest("inc", F.lit(theta))).alias("r"), F.count("*").alias("n_in"))
        )
        after, counts = cut_counted(paid.unionByName(sums(residue)), "shared-hop", nodes)
        discard(residue)
        residue = after
    found = sums(residue).select("qid", "rep", F.col("r").alias("pagerank"), F.col("n_in").alias("increments"))
    return targets.select("qid", "t").join(found, "qid").withColumn("method", F.lit(f"randomized_reverse_push_{draw}"))
