"""Two-phase methods: a reverse push, then walks that read what it left."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from nodeflux.functions.params import Params, blanket_r_max, blanket_walks, residue_r_max, residue_walks, subgraph_params
from nodeflux.plans.storage import cut

from .graph import Graph
from .push import edge_coin, sized
from .reverse import push_round, reverse_push, start_state
from .walks import walk_ends, walk_visits


def blanket(g: Graph, state: DataFrame, threshold: Column) -> DataFrame:
    """(qid, node, score): nodes whose reserve reaches the threshold, and their neighbours; score is the reserve."""
    heavy = state.filter(F.col("p") >= threshold).select("qid", "node")
    around = heavy.join(g.edges.select("src", "dst"), F.col("node") == F.col("src")).select("qid", F.col("dst").alias("node"))
    cover = heavy.union(around).distinct()
    return cover.join(state.select("qid", "node", "p"), ["qid", "node"], "left").select("qid", "node", F.coalesce("p", F.lit(0.0)).alias("score"))


def most_walks(g: Graph, targets: DataFrame, walks: Column) -> int:
    """The largest number of walks that any target asks for; one population serves all."""
    asked = g.nodes.filter("deg > 0").select(F.col("node").alias("t"), "deg").join(sized(targets.select("t")), "t")
    return int(asked.agg(F.max(walks)).first()[0] or 1)


def pushes(state: DataFrame, n_walks: int) -> DataFrame:
    """(qid, increments): pushed neighbours and walks."""
    return state.groupBy("qid").agg((F.sum("touched") + n_walks).alias("increments"))


def blanket_bidirectional(g: Graph, targets: DataFrame, p: Params = Params(), r_max: float | None = None, n_walks: int | None = None, cap: int | None = None, seed: int = 0, coin: str = "fast", rounds: int | None = None) -> DataFrame:
    """(qid, t, pagerank, method, increments): mean reserve of the first blanket node that a walk meets, its start included.

    Nodes are heavy from r_max on, but the push goes on to c times that: a reserve is then short by at most that share
    of what makes a node heavy, so scores are good within c. One population of walks serves all targets; a target keeps
    the first covered node of each walk. Without n_walks the method's own number is taken, the largest over the
    targets; without cap every walk is followed to its end.
    """
    limit = F.lit(float(r_max)) if r_max is not None else blanket_r_max(F.col("deg"), g.stats.n, p)
    n_walks = most_walks(g, targets, blanket_walks(F.col("deg"), g.stats.n, p)) if n_walks is None else n_walks
    state = reverse_push(g, targets, p, p.c * limit, rounds=rounds)
    per = sized(cut(g.nodes.select(F.col("node").alias("t"), "deg").join(sized(targets), "t").select("qid", limit.alias("limit")), "blanket-limits"))
    cover = sized(cut(blanket(g, state.join(per, "qid"), F.col("limit")), "blanket"))
    met = walk_visits(g, n_walks, p, cap, seed, coin).join(cover, "node")
    first = met.groupBy("qid", "wid").agg(F.min_by("score", "step").alias("score"))
    sums = first.groupBy("qid").agg((F.sum("score") / n_walks).alias("pagerank"))
    return targets.select("qid", "t").join(pushes(state, n_walks), "qid", "left").join(sums, "qid", "left").select(
        "qid", "t", F.coalesce("pagerank", F.lit(0.0)).alias("pagerank"), F.lit("blanket_bidirectional").alias("method"), "increments"
    )


def residue_bidirectional(g: Graph, targets: DataFrame, p: Params = Params(), r_max: float | None = None, n_walks: int | None = None, cap: int | None = None, seed: int = 0, coin: str = "fast", rounds: int | None = None) -> DataFrame:
    """(qid, t, pagerank, method, increments): mean reserve and the mean residue where walks stop; defaults as above."""
    limit = F.lit(float(r_max)) if r_max is not None else residue_r_max(F.col("deg"), g.stats.n, p)
    n_walks = most_walks(g, targets, residue_walks(limit, g.stats.n, p)) if n_walks is None else n_walks
    state = reverse_push(g, targets, p, limit, rounds=rounds)
    ends = walk_ends(g, n_walks, p, cap, seed, coin).groupBy("node").agg(F.count("*").alias("held"))
    reserve = state.groupBy("qid").agg((F.sum("p") / g.stats.n).alias("reserve"))
    rest = state.filter("r > 0").join(ends, "node").groupBy("qid").agg((F.sum(F.col("r") * F.col("held")) / n_walks).alias("rest"))
    return targets.select("qid", "t").join(reserve, "qid").join(pushes(state, n_walks), "qid").join(rest, "qid", "left").select(
        "qid", "t", (F.col("reserve") + F.coalesce("rest", F.lit(0.0))).alias("pagerank"), F.lit("residue_bidirectional").alias("method"), "increments"
    )


def subgraph_walks(g: Graph, targets: DataFrame, p: Params = Params(), n_walks: int | None = None, k: int | None = None, blacklist_deg: int | None = None, rounds: int = 3, cap: int | None = None, seed: int = 0, coin: str = "fast") -> DataFrame:
    """(qid, t, pagerank, method, increments): a reconstruction, as the method's mechanism is not described to us.

    k random partial explorations from t expand each frontier node below a degree bound with
    probability 1/2; each is finished by its own walks through the residue identity, which
    holds for any set of pushes; the mean over explorations is the answer. Walks are
    followed to their ends unless a cap is given.
    """
    n = g.stats.n
    walks, explorations, _ = subgraph_params(n, g.stats.max_deg, g.stats.avg_deg, p)
    walks, k = n_walks or walks, k or explorations
    each = max(1, walks // k)
    bound = blacklist_deg or max(2, round(10 * g.stats.avg_deg))
    deg = g.nodes.select("node", "deg")
    state = start_state(g, targets).withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(k - 1))))
    state = cut(state, "explore")
    for i in range(rounds):
        drawn = edge_coin(coin, F.lit(seed), F.lit(1_000_003 + i), F.col("qid"), F.col("rep"), F.col("node")) < 0.5
        chosen = (F.col("r") > 0) & (F.col("deg") <= bound) & (drawn if i else F.lit(True))
        state = cut(push_round(g, state.join(deg, "node"), chosen, p, ["qid", "rep"]), "explore")
    ended = walk_ends(g, each * k, p, cap, seed, coin).groupBy((F.col("wid") % k).cast("int").alias("rep"), "node").agg(F.count("*").alias("held"))
    reserve = state.groupBy("qid").agg((F.sum("p") / (n * k)).alias("reserve"))
    rest = state.filter("r > 0").join(ended, ["rep", "node"]).groupBy("qid").agg((F.sum(F.col("r") * F.col("held")) / (each * k)).alias("rest"))
    return targets.select("qid", "t").join(reserve, "qid").join(pushes(state, each * k), "qid").join(rest, "qid", "left").select(
        "qid", "t", (F.col("reserve") + F.coalesce("rest", F.lit(0.0))).alias("pagerank"), F.lit("subgraph_walks_reconstruction").alias("method"), "increments"
    )
