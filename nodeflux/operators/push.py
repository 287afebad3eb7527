"""The main method: outward push that pays in full where a neighbour's share is large and samples where it is small."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from nodeflux.functions.params import Params, hop_cap, theta_for
from nodeflux.functions.rng import u01_fast, u01_md5
from nodeflux.plans.storage import cut, cut_counted, discard

from . import blocks
from .graph import Graph

#: Broadcast a frontier only up to so many rows.
BROADCAST_ROWS = 200_000


@dataclass
class Estimates:
    """df(qid, rep, t, pagerank, theta, hops, increments, exact_increments, draws, method)."""

    df: DataFrame
    _vector: DataFrame | None = field(default=None, repr=False)

    def vector(self) -> DataFrame:
        """(qid, rep, node, value): unbiased personalised vector of t."""
        if self._vector is None:
            raise ValueError("ask for keep_vector=True")
        return self._vector


def plan_targets(g: Graph, targets: DataFrame, p: Params, theta: float | None, mode: str = "auto", reps: int = 1) -> DataFrame:
    """(qid, rep, t, deg, theta) of targets that are in the graph; each keeps its own row."""
    deg = g.nodes.select(F.col("node").alias("t"), "deg")
    at = F.lit(float(theta)) if theta is not None else theta_for(F.greatest(F.col("deg"), F.lit(1)), g.stats.n, g.stats.m, p, mode)
    rows = deg.join(sized(targets), "t").select("qid", "t", "deg", at.alias("theta"))
    return rows.withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))))


def sized(frontier: DataFrame, rows: float | None = None) -> DataFrame:
    """Broadcast hint behind a count of the rows (slim ones: targets, or a written frontier); else the join is left to Spark.

    rows is their number where the caller has it, which saves a job.
    """
    rows = frontier.count() if rows is None else rows
    return F.broadcast(frontier) if rows <= BROADCAST_ROWS else frontier


def edge_coin(kind: str, *key: Column | int) -> Column:
    return u01_md5(*key) if kind == "md5" else u01_fast(*key)


def binomial_law(deg: int, chance: float) -> np.ndarray:
    """Chances of 0 .. deg successes."""
    logs = np.concatenate([[0.0], np.cumsum(np.log(np.arange(1, deg + 1)))])
    k = np.arange(deg + 1)
    return np.exp(logs[deg] - logs[k] - logs[deg - k] + k * math.log(chance) + (deg - k) * math.log1p(-chance))


#: What tells a query and replica.
KEEP = ("qid", "rep", "theta", "t_deg")
#: Rows of sampled places.
PLACES = "qid int, rep int, theta double, t_deg long, node long, pos int"


def skip_positions(hop: int, seed: int, binomial: bool, coin: str = "fast"):
    """mapInArrow: (qid, rep, theta, t_deg, node, deg, chance) to PLACES, the sampled places of each list.

    Gaps between chosen places are geometric, so the work follows the sample and not the
    degree. A row's generator is keyed by its own identity. With coin "md5" the draws are those
    that SQL can repeat; "binomial" then inverts the law's sum and takes the places of least keys.
    """

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from nodeflux.functions.rng import u01_md5_np, u01_np

        uniform = u01_md5_np if coin == "md5" else u01_np
        for batch in batches:
            qid, rep, node, deg, chance = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("qid", "rep", "node", "deg", "chance"))
            rows, places = [np.zeros(0, dtype=np.int64)], [np.zeros(0, dtype=np.int64)]
            if binomial:
                for i in range(len(node)):
                    if coin == "md5":
                        keys = u01_md5_np(seed, hop, qid[i], rep[i], node[i], np.arange(deg[i] + 1))
                        k = int((np.cumsum(binomial_law(int(deg[i]), float(chance[i]))) < keys[0]).sum())
                        rows.append(np.full(k, i))
                        places.append(np.argsort(keys[1:], kind="stable")[:k] + 1)
                        continue
                    rng = np.random.default_rng([seed, hop, int(qid[i]), int(rep[i]), int(node[i])])
                    k = rng.binomial(int(deg[i]), float(chance[i]))
                    rows.append(np.full(k, i))
                    places.append(rng.choice(int(deg[i]), size=k, replace=False) + 1)
            else:
                live, at, draw = np.arange(len(node)), np.zeros(len(node), dtype=np.int64), 0
                scale = np.log1p(-np.minimum(chance, 1 - 1e-16))
                while len(live):
                    u = uniform(seed, hop, qid[live], rep[live], node[live], draw)
                    gap = 1 + np.floor(np.log(u) / scale[live])
                    at[live] = at[live] + np.minimum(gap, deg[live] + 1.0).astype(np.int64)
                    live = live[at[live] <= deg[live]]
                    rows.append(live)
                    places.append(at[live].copy())
                    draw += 1
            i, pos = pa.array(np.concatenate(rows)), pa.array(np.concatenate(places).astype(np.int32))
            held = [batch.column(c).take(i) for c in ("qid", "rep", "theta", "t_deg", "node")]
            yield pa.RecordBatch.from_arrays([*held, pos], ["qid", "rep", "theta", "t_deg", "node", "pos"])

    return read


def share(p: Params) -> Column:
    """What a node pays to each neighbour; it samples below theta."""
    return (1 - p.alpha) * F.col("r") / F.col("deg")


def tally(p: Params) -> list[Column]:
    """Aggregates that plan a hop's joins: nodes, those that sample, and the expected number of sampled places."""
    light = share(p) < F.col("theta")
    places = F.sum(F.when(light, F.try_divide((1 - p.alpha) * F.col("r"), F.col("theta"))))
    return [F.count("node").alias("nodes"), F.count_if(light).alias("light"), F.coalesce(places, F.lit(0.0)).alias("places")]


def next_residue(g: Graph, residue: DataFrame, p: Params, hop: int, seed: int, sampler: str, coin: str, counts: dict | None = None) -> DataFrame:
    """residue(qid, rep, theta, t_deg, node, deg, r) one hop on; also n_in, n_exact: increments that made each row, and n_draws: its places.

    counts are the residue's `tally`. What no node does in this hop (pay in full, sample) is not planned.
    """
    counts = residue.agg(*tally(p)).first().asDict() if counts is None else counts
    marked = residue.withColumn("share", share(p))
    edges = g.around(residue).select("src", "dst", "pos", F.col("dst_deg").alias("deg_in"))
    none = F.lit(0).cast("long")
    if sampler == "edge":
        joined = sized(marked, counts["nodes"]).join(edges, F.col("node") == F.col("src"))
        full = F.col("share") >= F.col("theta")
        draw = edge_coin(coin, F.lit(seed), F.col("qid"), F.col("rep"), F.lit(hop), F.col("src"), F.col("dst"))
        taken = full | (draw < F.try_divide("share", "theta"))
        paid = joined.filter(taken).select(*KEEP, "dst", "deg_in", F.greatest("share", "theta").alias("inc"), full.cast("long").alias("is_full"), none.alias("n_draws"))
    else:
        heavy = sized(marked.filter("share >= theta"), counts["nodes"] - counts["light"]).join(edges, F.col("node") == F.col("src"))
        paid = heavy.select(*KEEP, "dst", "deg_in", F.col("share").alias("inc"), F.lit(1).cast("long").alias("is_full"), none.alias("n_draws"))
        if counts["light"]:
            typed = [F.col(c).cast(kind).alias(c) for c, kind in (part.split() for part in PLACES.split(", ")[:-1])]
            light = marked.filter("share < theta").select(*typed, F.col("deg").cast("long").alias("deg"), (F.col("share") / F.col("theta")).alias("chance"))
            chosen = light.mapInArrow(skip_positions(hop, seed, sampler == "binomial", coin), PLACES).withColumnRenamed("pos", "place")
            # Spark cannot know how many places a row gives: the join follows their expected number, ten deviations up
            many = counts["places"] + 10 * math.sqrt(counts["places"])
            chosen = F.broadcast(chosen) if many <= BROADCAST_ROWS else chosen.hint("merge")
            picked = chosen.join(edges, (F.col("node") == F.col("src")) & (F.col("pos") == F.col("place")))
            picked = picked.select(*KEEP, "dst", "deg_in", F.col("theta").alias("inc"), none.alias("is_full"), F.lit(1).cast("long").alias("n_draws"))
            paid = paid.union(picked) if counts["light"] < counts["nodes"] else picked
    return paid.groupBy(*KEEP, F.col("dst").alias("node"), F.col("deg_in").alias("deg")).agg(
        F.sum("inc").alias("r"), F.count("*").alias("n_in"), F.sum("is_full").alias("n_exact"), F.sum("n_draws").alias("n_draws")
    )


def totals(residue: DataFrame, p: Params, n: int, sampler: str | None = None) -> DataFrame:
    """A row for each query and replica, node null: its PageRank in r, its increments and draws up to this hop.

    With a sampler the draws of the hop to come that choose nothing are added: every coin ("edge"), or one a node that
    samples ("skip": the gap beyond the list's end, "binomial": the number); places were counted where they were chosen.
    """
    part = F.when(F.col("node").isNull(), F.col("r")).otherwise(p.alpha * F.col("t_deg") * F.col("r") / (n * F.col("deg")))
    drawn = F.lit(0) if sampler is None else F.when(share(p) < F.col("theta"), F.col("deg") if sampler == "edge" else F.lit(1)).otherwise(0)
    empty = F.lit(None).cast("long")
    sums = residue.groupBy(*KEEP).agg(
        F.sum(part).alias("r"), F.sum("n_in").alias("n_in"), F.sum("n_exact").alias("n_exact"), F.sum(F.col("n_draws") + drawn).alias("n_draws")
    )
    return sums.select(*KEEP, empty.alias("node"), empty.alias("deg"), "r", "n_in", "n_exact", "n_draws")


def adaptive_push(
    g: Graph,
    targets: DataFrame,
    p: Params = Params(),
    theta: float | None = None,
    hops: int | None = None,
    sampler: str = "skip",
    seed: int = 0,
    reps: int = 1,
    mode: str = "auto",
    coin: str = "fast",
    keep_vector: bool = False,
) -> Estimates:
    """PageRank of each target (qid, t). A hop's contribution is folded into one row a query, then the hop is dropped.

    A hop is one job: its table holds the residue and the queries' totals so far, and is counted while it is written, so the
    driver sees three numbers a hop, however many queries there are. A target without edges has PageRank 1 / n; a target
    that is not in the graph gives no row.
    """
    n = g.stats.n
    hops = hop_cap(n, p) if hops is None else hops
    plan = cut(plan_targets(g, targets, p, theta, mode, reps), "push-plan")
    if theta == 0 and not keep_vector and g.adj is None and 0 < plan.count() <= blocks.SLOTS:
        return _estimates(g, plan, exact_sums(g, plan, p, hops), hops)
    start = plan.filter("deg > 0").select(
        "qid", "rep", "theta", F.col("deg").alias("t_deg"), F.col("t").alias("node"), "deg", F.lit(1.0).alias("r"),
        *[F.lit(0).cast("long").alias(c) for c in ("n_in", "n_exact", "n_draws")],
    )
    residue, counts = cut_counted(start, "push-hop", tally(p))
    vectors = []
    for hop in range(hops + 1):
        if keep_vector:
            vectors.append(residue.filter("node is not null").select("qid", "rep", "node", (p.alpha * F.col("r")).alias("value")))
        if hop == hops or not counts["nodes"]:
            break
        paid = next_residue(g, residue.filter("node is not null"), p, hop, seed, sampler, coin, counts)
        after, counts = cut_counted(paid.unionByName(totals(residue, p, n, sampler)), "push-hop", tally(p))
        if not keep_vector:
            discard(residue)
        residue = after
    sums = totals(residue, p, n).select("qid", "rep", F.col("r").alias("pagerank"), F.col("n_in").alias("increments"), F.col("n_exact").alias("exact_increments"), F.col("n_draws").alias("draws"))
    estimates = _estimates(g, plan, sums, hops)
    if keep_vector:
        vector = vectors[0]
        for v in vectors[1:]:
            vector = vector.union(v)
        estimates._vector = vector.groupBy("qid", "rep", "node").agg(F.sum("value").alias("value"))
    return estimates


def exact_sums(g: Graph, plan: DataFrame, p: Params, hops: int) -> DataFrame:
    """What the queries of a plan whose theta is 0 sum to: nothing is sampled, so a hop is a product of blocks with all queries' vectors.

    The driver sees the plan, at most blocks.SLOTS rows.
    """
    asked = plan.filter("deg > 0").select("qid", "rep", "t", "deg").orderBy("qid", "rep", "t").collect()
    slots = g.spark.createDataFrame([(i, *r) for i, r in enumerate(asked)], "slot int, qid int, rep int, t long, deg long")
    start = slots.select("slot", F.col("t").alias("node"), F.lit(1.0).alias("r"))
    held = blocks.sums(g, blocks.series(g, start, max(1, len(asked)), 1 - p.alpha, [p.alpha] * (hops + 1)), max(1, len(asked)))
    cost = F.col("cost")
    return slots.join(held, "slot").groupBy("qid", "rep").agg(
        F.sum(F.col("deg") * F.col("by_deg") / g.stats.n).alias("pagerank"), F.sum(cost).alias("increments"), F.sum(cost).alias("exact_increments"), F.sum(F.lit(0)).alias("draws")
    )


def _estimates(g: Graph, plan: DataFrame, sums: DataFrame, hops: int) -> Estimates:
    n = g.stats.n
    df = plan.join(sums, ["qid", "rep"], "left").select(
        "qid", "rep", "t",
        F.when(F.col("deg") == 0, 1.0 / n).otherwise(F.col("pagerank")).alias("pagerank"),
        "theta", F.lit(hops).alias("hops"),
        *[F.coalesce(F.col(c), F.lit(0)).cast("long").alias(c) for c in ("increments", "exact_increments", "draws")],
        F.lit("adaptive_push").alias("method"),
    )
    return Estimates(df)


def amplified(estimates: DataFrame, groups: int = 1) -> DataFrame:
    """(qid, t, pagerank): the median over replicas, or of the means of `groups` groups of them."""
    if groups > 1:
        estimates = estimates.groupBy("qid", "t", F.pmod("rep", F.lit(groups)).alias("rep")).agg(F.avg("pagerank").alias("pagerank"))
    return estimates.groupBy("qid", "t").agg(F.percentile("pagerank", 0.5).alias("pagerank"))
