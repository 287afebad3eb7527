"""Registered queries of the engine and, where SQL can say the same, their DuckDB texts."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from nodeflux.functions import params as pm
from nodeflux.functions.params import Params
from nodeflux.operators import accuracy as acc
from nodeflux.operators import bidirectional as bi
from nodeflux.operators import exact as ex
from nodeflux.operators import graph as gr
from nodeflux.operators import reverse as rv
from nodeflux.operators import walks as wk
from nodeflux.operators import workloads as wl
from nodeflux.operators.estimate import single_node_pagerank
from nodeflux.operators.push import adaptive_push, amplified
from nodeflux.operators.targets import degree_targets, stratified_targets, uniform_targets
from nodeflux.plans import oracles as o
from nodeflux.sources.graphs import GRAPHS
from nodeflux.sources.tables import load

P = Params()
Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def register(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def put(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return put


def r6(c: Column | str) -> Column:
    return F.round(F.col(c) if isinstance(c, str) else c, 6)


def npi(g: gr.Graph, c: str = "pagerank") -> Column:
    return F.round(F.col(c) * g.stats.n, 6).alias("n_pi")


# -- graphs ---------------------------------------------------------------------------------

for _name in ("purchase", "tree", "session", "links", "leak", "knn"):

    @register(f"graph_edges_{_name}", o.query(_name, final="SELECT src, dst, pos, src_deg, dst_deg FROM e"))
    def _edges(spark: SparkSession, sf: str, name: str = _name) -> DataFrame:
        return gr.graph(spark, sf, name).edges.select("src", "dst", F.col("pos").cast("long").alias("pos"), "src_deg", "dst_deg")


@register("graph_stats", " UNION ALL ".join(
    f"SELECT * FROM ({o.query(k, final=f'''SELECT '{k}' AS graph, n, m::BIGINT AS m, max_deg, round(2.0 * m / n, 6) AS avg_deg FROM st''')})" for k in GRAPHS))
def graph_stats(spark: SparkSession, sf: str) -> DataFrame:
    rows = [(k, s.n, s.m, s.max_deg, round(s.avg_deg, 6)) for k in GRAPHS for s in [gr.stats(spark, sf, k)]]
    return spark.createDataFrame(rows, "graph string, n long, m long, max_deg long, avg_deg double")


@register("degree_histogram", o.query("terms", final="SELECT deg, count(*) AS nodes FROM nd GROUP BY deg"))
def degree_histogram(spark: SparkSession, sf: str) -> DataFrame:
    return gr.graph(spark, sf, "terms").nodes.groupBy("deg").agg(F.count("*").alias("nodes"))


@register("degree_quantiles", o.query("supply", final="SELECT quantile_cont(deg, 0.1) AS p10, quantile_cont(deg, 0.5) AS p50, quantile_cont(deg, 0.9) AS p90 FROM nd"))
def degree_quantiles(spark: SparkSession, sf: str) -> DataFrame:
    return gr.graph(spark, sf, "supply").nodes.agg(*[F.percentile("deg", q).alias(f"p{round(q * 100)}") for q in (0.1, 0.5, 0.9)])


@register("node_ids", o.query("order", final="SELECT node, key, deg FROM nd"))
def node_ids(spark: SparkSession, sf: str) -> DataFrame:
    return gr.graph(spark, sf, "order").nodes.select("node", "key", "deg")


@register("adjacency_blocks", o.query("supply", final="""SELECT src, (pos - 1) // 64 AS block, count(*) AS held, string_agg(dst::VARCHAR, ',' ORDER BY pos) AS nbr
 FROM e GROUP BY src, (pos - 1) // 64"""))  # fmt: skip
def adjacency_blocks(spark: SparkSession, sf: str) -> DataFrame:
    adj = gr.block(gr.graph(spark, sf, "supply").edges, 64)
    return adj.select("src", F.col("block").cast("long").alias("block"), F.size("nbr").cast("long").alias("held"), F.array_join("nbr", ",").alias("nbr"))


@register("graph_store", o.query("tree", final="SELECT src, dst, pos, src_deg, dst_deg FROM e"))
def graph_store(spark: SparkSession, sf: str) -> DataFrame:
    """Write the bucketed adjacency and open it again."""
    import uuid

    from nodeflux.plans.storage import shared_dir

    path = f"{shared_dir(spark)}/graph-{uuid.uuid4().hex}"
    gr.graph(spark, sf, "tree").write(path, 8)
    return gr.Graph.open(spark, path).edges.withColumn("pos", F.col("pos").cast("long"))


@register("components_tree", o.query("tree", """cc AS (SELECT node, node AS comp FROM nd UNION SELECT dst AS node, comp FROM cc JOIN e ON node = src)""",
                                     final="SELECT node, min(comp) AS comp FROM cc GROUP BY node"))
def components_tree(spark: SparkSession, sf: str) -> DataFrame:
    return gr.components(gr.graph(spark, sf, "tree"))


@register("common_neighbours", o.query("supply", targets=o.uniform(8), final="""SELECT x.t AS u, y.t AS v, count(*) AS common FROM tg x JOIN tg y ON x.t < y.t
 JOIN e a ON a.src = x.t JOIN e b ON b.src = y.t AND b.dst = a.dst GROUP BY x.t, y.t"""))  # fmt: skip
def common_neighbours(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "supply")
    t = uniform_targets(g, 8)
    return gr.common_neighbours(g, t.select(F.col("t").alias("u")).join(t.select(F.col("t").alias("v")), F.col("u") < F.col("v")))


_DAY = "SELECT DISTINCT 'u:' || user_id AS a, 'h:' || event_type || '/' || hour(ts) AS b FROM events WHERE day(ts) = "


@register("edge_diff", f"SELECT a, b, 'added' AS change FROM ({_DAY}2 EXCEPT {_DAY}1) UNION ALL SELECT a, b, 'removed' FROM ({_DAY}1 EXCEPT {_DAY}2)")
def edge_diff(spark: SparkSession, sf: str) -> DataFrame:
    events = load(spark, sf, "events")

    def of(day: int) -> DataFrame:
        key = F.concat(F.lit("h:"), F.concat_ws("/", "event_type", F.hour("ts").cast("string")))
        return events.filter(F.dayofmonth("ts") == day).select(F.concat(F.lit("u:"), F.col("user_id").cast("string")).alias("a"), key.alias("b")).distinct()

    return gr.edge_diff(of(1), of(2))


@register("source_roundtrip", o.query("tree", final="SELECT fmt, count(*) AS edges, count(DISTINCT a) AS nodes FROM bo, (SELECT unnest(['csv', 'json', 'orc', 'parquet', 'text']) AS fmt) GROUP BY fmt"))
def source_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    """The same raw edges through every file format."""
    import uuid

    from nodeflux.plans.storage import shared_dir
    from nodeflux.sources.tables import read_edges

    raw, base, out = GRAPHS["tree"](spark, sf), f"{shared_dir(spark)}/edges-{uuid.uuid4().hex}", None
    for fmt in ("csv", "json", "orc", "parquet", "text"):
        written = raw.select(F.concat_ws(" ", "a", "b").alias("value")) if fmt == "text" else raw
        written.write.format(fmt).option("header", True).save(f"{base}/{fmt}")
        both = gr.normalise(read_edges(spark, fmt, f"{base}/{fmt}", "a", "b", **({"header": "true"} if fmt == "csv" else {})))
        part = both.agg(F.lit(fmt).alias("fmt"), F.count("*").alias("edges"), F.countDistinct("a").alias("nodes"))
        out = part if out is None else out.union(part)
    return out


# -- exact methods -----------------------------------------------------------------------------

for _name in ("purchase", "tree", "links"):

    @register(f"power_iteration_{_name}", o.query(_name, o.power(10), final="SELECT node, round(pi * n, 6) AS n_pi FROM pw, st WHERE i = 10"))
    def _power(spark: SparkSession, sf: str, name: str = _name) -> DataFrame:
        g = gr.graph(spark, sf, name)
        return ex.power_iteration(g, P, 10).select("node", npi(g, "pi"))


#: Hops of the results that SQL repeats: they are vectors limited to so many hops. The queries named _whole take the hop cap.
H = 6
_TRUNC = [0.2] * (H + 1)


@register("truncated_pagerank", o.query("supply", o.series(o.UNIFORM_START, "", 0.8, _TRUNC), final="SELECT node, round(value * n, 6) AS n_pi FROM sv, st"))
def truncated_pagerank(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "supply")
    return ex.truncated_pagerank(g, P, H).select("node", npi(g, "pi"))


@register("hop_ppr", o.query("purchase", o.series(o.ONE_HOT, "qid", 0.8, [0.0, 0.0, 0.2]), targets=o.uniform(5), final="SELECT qid, node, round(value, 8) AS value FROM sv WHERE value > 0"))
def hop_ppr(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "purchase")
    return ex.hop_ppr(g, uniform_targets(g, 5), 2, P).select("qid", "node", F.round("value", 8).alias("value"))


@register("ppr_from", o.query("tree", o.series(o.ONE_HOT, "qid", 0.8, _TRUNC), targets=o.uniform(5), final="SELECT qid, node, round(value, 8) AS value FROM sv"))
def ppr_from(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    return ex.ppr_from(g, uniform_targets(g, 5), P, H).select("qid", "node", F.round("value", 8).alias("value"))


@register("ppr_to", o.query("supply", o.series(o.ONE_HOT, "qid", 0.8, _TRUNC[:5]), targets=o.uniform(5), final="""SELECT qid, sv.node, round(value * a.deg / b.deg, 8) AS value
 FROM sv JOIN tg USING (qid) JOIN nd a ON a.node = tg.t JOIN nd b ON b.node = sv.node"""))  # fmt: skip
def ppr_to(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "supply")
    return ex.ppr_to(g, uniform_targets(g, 5), P, 4).select("qid", "node", F.round("value", 8).alias("value"))


@register("heat_kernel", o.query("links", o.series(o.ONE_HOT, "qid", 1.0, o.poisson(2.0, 6)), targets=o.uniform(5), final="SELECT qid, node, round(value, 8) AS value FROM sv"))
def heat_kernel(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "links")
    return ex.heat_kernel(g, uniform_targets(g, 5), 2.0, 6).select("qid", "node", F.round("value", 8).alias("value"))


@register("weighted_ppr", """WITH RECURSIVE w AS MATERIALIZED (SELECT o_custkey AS c, l_suppkey AS s, sum(l_quantity) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL),
 b AS MATERIALIZED (SELECT c AS src, -s - 1 AS dst, q FROM w UNION ALL SELECT -s - 1, c, q FROM w), k AS MATERIALIZED (SELECT src, sum(q) AS q FROM b GROUP BY src),
 r AS (SELECT 0 AS hop, (SELECT min(c) FROM w) AS node, 1.0::DOUBLE AS r UNION ALL
  SELECT hop + 1 AS hop, dst AS node, sum(0.8 * r * b.q / k.q) AS r FROM r JOIN b ON node = b.src JOIN k ON node = k.src WHERE hop < 4 GROUP BY ALL)
 SELECT 0 AS qid, node, round(sum(0.2 * r), 8) AS value FROM r GROUP BY node""")  # fmt: skip
def weighted_ppr(spark: SparkSession, sf: str) -> DataFrame:
    orders, items = load(spark, sf, "orders"), load(spark, sf, "lineitem")
    w = orders.join(items, F.col("o_orderkey") == F.col("l_orderkey")).groupBy(F.col("o_custkey").alias("c"), F.col("l_suppkey").alias("s")).agg(F.sum("l_quantity").alias("weight"))
    both = w.select(F.col("c").alias("src"), (-F.col("s") - 1).alias("dst"), "weight").union(w.select(-F.col("s") - 1, "c", "weight"))
    t = w.agg(F.min("c").alias("t")).select(F.lit(0).alias("qid"), "t")
    return ex.weighted_ppr(both, t, P, 4).select("qid", "node", F.round("value", 8).alias("value"))


# -- the main method ------------------------------------------------------------------------------

_EST = "SELECT qid, t, round(pagerank * n, 6) AS n_pi, increments::BIGINT AS increments, exact_increments::BIGINT AS exact_increments FROM pe, st"


def _est(g: gr.Graph, df: DataFrame) -> DataFrame:
    return df.select("qid", "t", npi(g), "increments", "exact_increments")


for _label, _graph, _theta in (("exact", "purchase", 0.0), ("edge", "purchase", 1e-3), ("edge_terms", "terms", 1e-2), ("quantised", "tree", 1.0)):

    @register(f"adaptive_push_{_label}", o.query(_graph, o.push(repr(_theta), H), targets=o.uniform(5), final=_EST))
    def _push(spark: SparkSession, sf: str, name: str = _graph, theta: float = _theta) -> DataFrame:
        g = gr.graph(spark, sf, name)
        return _est(g, adaptive_push(g, uniform_targets(g, 5), P, theta=theta, hops=H, sampler="edge", coin="md5").df)


@register("adaptive_push_degree_targets", o.query("supply", o.push(o.theta_auto("n", "m", "(SELECT deg FROM nd WHERE nd.node = tg.t)", 0.5).join(["(SELECT ", " FROM st)"]), 3), targets=o.by_degree(4), final=_EST))
def adaptive_push_degree_targets(spark: SparkSession, sf: str) -> DataFrame:
    """theta from the schedule, for targets drawn by degree at c = 0.5."""
    g = gr.graph(spark, sf, "supply")
    return _est(g, adaptive_push(g, degree_targets(g, 4), P.but(c=0.5), hops=3, sampler="edge", coin="md5").df)


# thetas with more digits than the results keep, so that no result is a tie of rounding
for _label, _graph, _theta in (("exact", "purchase", 0.0), ("edge", "purchase", 1.07123e-3), ("edge_terms", "terms", 1.07123e-2), ("quantised", "tree", 1.07123)):

    @register(f"adaptive_push_{_label}_whole", o.query(_graph, o.push(repr(_theta), o.WHOLE), targets=o.uniform(5), final=_EST))
    def _push_whole(spark: SparkSession, sf: str, name: str = _graph, theta: float = _theta) -> DataFrame:
        g = gr.graph(spark, sf, name)
        return _est(g, adaptive_push(g, uniform_targets(g, 5), P, theta=theta, sampler="edge", coin="md5").df)


@register("adaptive_push_degree_targets_whole", o.query("supply", o.push(o.theta_auto("n", "m", "(SELECT deg FROM nd WHERE nd.node = tg.t)", 0.5).join(["(SELECT ", " FROM st)"]), o.WHOLE_LOOSE), targets=o.by_degree(4), final=_EST))
def adaptive_push_degree_targets_whole(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "supply")
    return _est(g, adaptive_push(g, degree_targets(g, 4), P.but(c=0.5), sampler="edge", coin="md5").df)


@register("truncated_pagerank_whole", o.query("supply", f"""tp AS (SELECT 0 AS hop, node, 1.0::DOUBLE / n AS r FROM nd, st
 UNION ALL SELECT hop + 1 AS hop, dst AS node, sum(0.8 * r / src_deg) AS r FROM tp JOIN e ON node = src WHERE hop < {o.WHOLE} GROUP BY ALL)""",
    final="SELECT node, round(sum(0.2 * r) * any_value(n), 6) AS n_pi FROM tp, st GROUP BY node"))
def truncated_pagerank_whole(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "supply")
    return ex.truncated_pagerank(g, P).select("node", npi(g, "pi"))


@register("ppr_from_whole", o.query("tree", f"""tp AS (SELECT 0 AS hop, qid, t AS node, 1.0::DOUBLE AS r FROM tg
 UNION ALL SELECT hop + 1 AS hop, qid, dst AS node, sum(0.8 * r / src_deg) AS r FROM tp JOIN e ON node = src WHERE hop < {o.WHOLE} GROUP BY ALL)""",
    targets=o.uniform(5), final="SELECT qid, node, round(sum(0.2 * r), 8) AS value FROM tp GROUP BY qid, node"))
def ppr_from_whole(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    return ex.ppr_from(g, uniform_targets(g, 5), P, pm.hop_cap(g.stats.n, P)).select("qid", "node", F.round("value", 8).alias("value"))


_ERRORS = """SELECT round(avg(rel), 6) AS mean_error_over_c, round(max(rel), 6) AS max_error_over_c,
 avg((rel > 1)::INT)::DOUBLE AS failure_rate, count(*) AS queries, method FROM (SELECT 'adaptive_push' AS method, abs(pagerank - pi) / pi / 0.1 AS rel FROM pe JOIN pw ON t = node AND i = 100) GROUP BY ROLLUP (method)"""


@register("relative_error_report_whole", o.query("tree", o.places(o.theta_auto("n", "m", "deg"), o.WHOLE), o.power(100), targets=o.uniform(10), final=_ERRORS))
def relative_error_report_whole(spark: SparkSession, sf: str) -> DataFrame:
    """The method's own schedule and hop cap against 100 power iterations."""
    g = gr.graph(spark, sf, "tree")
    est = adaptive_push(g, uniform_targets(g, 10), P, coin="md5").df
    rows = acc.error_report(acc.relative_error(est, wl.truth(g, P)), P, ["method"])
    return rows.select("method", r6("mean_error_over_c").alias("mean_error_over_c"), r6("max_error_over_c").alias("max_error_over_c"), "failure_rate", "queries")


@register("adaptive_push_vector", o.query("tree", o.push("0.01", H), targets=o.uniform(5), final="SELECT qid, node, round(sum(0.2 * r), 8) AS value FROM ph GROUP BY qid, node"))
def adaptive_push_vector(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    got = adaptive_push(g, uniform_targets(g, 5), P, theta=0.01, hops=H, sampler="edge", coin="md5", keep_vector=True)
    return got.vector().select("qid", "node", F.round("value", 8).alias("value"))


@register("median_amplified", o.query("tree", o.push("0.0193", H, reps=5), targets=o.uniform(5), final="SELECT qid, t, round(quantile_cont(pagerank, 0.5) * any_value(n), 6) AS n_pi FROM pe, st GROUP BY qid, t"))
def median_amplified(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    return amplified(adaptive_push(g, uniform_targets(g, 5), P, theta=0.0193, hops=H, sampler="edge", coin="md5", reps=5).df).select("qid", "t", npi(g))


for _sampler in ("skip", "binomial"):

    @register(f"adaptive_push_{_sampler}", o.query("supply", o.places("0.00507123", o.WHOLE, _sampler == "binomial"), targets=o.uniform(5),
              final=_EST.replace(" FROM", ", draws::BIGINT AS draws FROM")))
    def _sampled(spark: SparkSession, sf: str, sampler: str = _sampler) -> DataFrame:
        g = gr.graph(spark, sf, "supply")
        df = adaptive_push(g, uniform_targets(g, 5), P, theta=0.00507123, sampler=sampler, coin="md5").df
        return df.select("qid", "t", npi(g), "increments", "exact_increments", "draws")


@register("adaptive_push_resident")
def adaptive_push_resident(spark: SparkSession, sf: str) -> DataFrame:
    """All hops and the default schedule, in the resident engine, beside the truth."""
    rows = wl.run_query_set(spark, sf, ["purchase"], ("adaptive_push",), "uniform", P)
    return rows.select("qid", "t", "pagerank", "truth", "error_over_c", "increments", "exact_increments", "draws")


# -- baselines ----------------------------------------------------------------------------------------

_REV = "SELECT qid, t, round(sum(p), 6) AS n_pi, sum(touched)::BIGINT AS increments FROM rv JOIN tg USING (qid) WHERE round = {r} GROUP BY qid, t"


@register("reverse_push_sync", o.query("supply", o.ADJ, o.reverse("0.002", 40), targets=o.uniform(5), final=_REV.format(r=40)))
def reverse_push_sync(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "supply")
    t = uniform_targets(g, 5)
    return rv.mean_reserve(g, t, rv.reverse_push(g, t, P, 0.002), "reverse_push").select("qid", "t", npi(g), "increments")


@register("reverse_push_priority")
def reverse_push_priority(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    t = uniform_targets(g, 5)
    return rv.mean_reserve(g, t, rv.reverse_push(g, t, P, order="priority", batch=1024), "reverse_push_priority").select("qid", "t", npi(g), "increments")


for _draw in ("shared", "edge"):

    @register(f"randomized_reverse_push_{_draw}", o.query("purchase", o.randomized(1e-3, 5, _draw == "edge"), targets=o.uniform(5),
              final="SELECT qid, t, round(sum(0.2 * r), 6) AS n_pi, sum(n_in)::BIGINT AS increments FROM rz JOIN tg USING (qid) GROUP BY qid, t"))
    def _randomized(spark: SparkSession, sf: str, draw: str = _draw) -> DataFrame:
        g = gr.graph(spark, sf, "purchase")
        return rv.randomized_reverse_push(g, uniform_targets(g, 5), P, 1e-3, draw, 5, coin="md5").select("qid", "t", npi(g), "increments")


@register("walk_sample", o.query("supply", o.walks(2000, 1000), targets=o.uniform(20), final="SELECT qid, t, round(count(wid) / 2000.0, 8) AS pagerank FROM tg LEFT JOIN wk ON node = t AND stop GROUP BY qid, t"))
def walk_sample(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "supply")
    return wk.walk_sample(g, uniform_targets(g, 20), P, 2000, coin="md5").select("qid", "t", F.round("pagerank", 8).alias("pagerank"))


@register("walk_length_stats", o.query("tree", o.walks(1500, 1000), final="SELECT count(*) AS walks, round(avg(step), 6) AS mean_moves, 4.0::DOUBLE AS expected FROM wk WHERE stop"))
def walk_length_stats(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    return wk.walk_length_stats(wk.walk_ends(g, 1500, P, None, 0, "md5"), P).select("walks", r6("mean_moves").alias("mean_moves"), F.round("expected", 6).alias("expected"))


@register("residue_bidirectional", o.query("tree", o.ADJ, o.reverse("0.05", 30), o.walks(1000, 1000), targets=o.uniform(5), final="""SELECT qid, tg.t, round(x.s + coalesce(y.s, 0) / 1000.0 * n, 6) AS n_pi FROM tg
 JOIN (SELECT qid, sum(p) AS s FROM rv WHERE round = 30 GROUP BY qid) x USING (qid)
 LEFT JOIN (SELECT qid, sum(r) AS s FROM rv JOIN wk ON rv.node = wk.node AND wk.stop WHERE round = 30 GROUP BY qid) y USING (qid), st"""))  # fmt: skip
def residue_bidirectional(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    return bi.residue_bidirectional(g, uniform_targets(g, 5), P, 0.05, 1000, coin="md5").select("qid", "t", npi(g))


@register("blanket_bidirectional", o.query("tree", o.ADJ, o.reverse("0.005", 40), o.walks(1000, 1000), """hv AS (SELECT qid, node FROM rv WHERE round = 40 AND p >= 0.05),
cv AS (SELECT DISTINCT qid, node FROM (SELECT qid, node FROM hv UNION ALL SELECT qid, dst FROM hv JOIN e ON node = src)),
sc AS (SELECT cv.qid, cv.node, coalesce(p, 0) AS score FROM cv LEFT JOIN rv ON rv.round = 40 AND rv.qid = cv.qid AND rv.node = cv.node),
ft AS (SELECT qid, wid, arg_min(score, step) AS score FROM wk JOIN sc USING (node) GROUP BY qid, wid)""", targets=o.uniform(5),
    final="SELECT qid, t, round(coalesce(sum(score), 0) / 1000.0 * any_value(n), 6) AS n_pi FROM tg LEFT JOIN ft USING (qid), st GROUP BY qid, t"))
def blanket_bidirectional(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    return bi.blanket_bidirectional(g, uniform_targets(g, 5), P, 0.05, 1000, coin="md5").select("qid", "t", npi(g))


@register("subgraph_walks")
def subgraph_walks(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    return bi.subgraph_walks(g, uniform_targets(g, 5), P).select("qid", "t", npi(g), "method")


@register("subgraph_walks_keyed", o.query("tree", o.ADJ, o.explore(4, 3, 20), o.walks(1000, 1000), targets=o.uniform(5), final="""SELECT qid, tg.t, round(x.s / 4 + coalesce(y.s, 0) / 1000.0 * n, 6) AS n_pi FROM tg
 JOIN (SELECT qid, sum(p) AS s FROM sx WHERE round = 3 GROUP BY qid) x USING (qid)
 LEFT JOIN (SELECT qid, sum(r) AS s FROM sx JOIN wk ON sx.node = wk.node AND wk.stop AND wk.wid % 4 = sx.rep WHERE round = 3 GROUP BY qid) y USING (qid), st"""))  # fmt: skip
def subgraph_walks_keyed(spark: SparkSession, sf: str) -> DataFrame:
    """Four explorations and 1000 walks, few enough for SQL to repeat."""
    g = gr.graph(spark, sf, "tree")
    return bi.subgraph_walks(g, uniform_targets(g, 5), P, 1000, 4, 20, coin="md5").select("qid", "t", npi(g))


for _method in wl.METHODS[1:]:

    @register(f"baseline_{_method}")
    def _baseline(spark: SparkSession, sf: str, method: str = _method) -> DataFrame:
        """By the method's own formulas, with whole walks and all rounds, beside the truth; no SQL, as it would be too slow."""
        rows = wl.run_query_set(spark, sf, ["supply", "tree"], (method,), "uniform", P, k=5)
        return rows.select("graph", "qid", "t", "pagerank", "truth", "error_over_c", "increments", "seconds")


@register("walk_length_whole")
def walk_length_whole(spark: SparkSession, sf: str) -> DataFrame:
    """Moves of walks that are all followed to their end, so that the mean is not biased by a cap."""
    return wk.walk_length_stats(wk.walk_ends(gr.graph(spark, sf, "tree"), 20_000, P, None, 0), P)


# -- parameters, measures ------------------------------------------------------------------------------

@register("theta_schedule", o.query("supply", final=f"""SELECT node, deg, round(ln(0.2 * 0.01 * 0.1 / (4 * {o.hop_cap("n")}) / deg), 9) AS by_degree,
 round(ln(0.2 * 0.01 * 0.1 / (4 * {o.hop_cap("n")}) * sqrt(1.6 / m)), 9) AS by_edges, round(ln({o.theta_auto("n", "m", "deg")}), 9) AS auto FROM nd, st"""))  # fmt: skip
def theta_schedule(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "supply")
    ln = lambda mode: F.round(F.log(pm.theta_for(F.col("deg"), g.stats.n, g.stats.m, P, mode)), 9)
    return g.nodes.select("node", "deg", ln("degree").alias("by_degree"), ln("edges").alias("by_edges"), ln("auto").alias("auto"))


@register("method_parameters", o.query("purchase", targets=o.uniform(10), final=f"""SELECT t, deg, round(ln(0.1 * 0.2 / n), 9) AS push_eps,
 round(ln(0.1 * sqrt(0.2 * deg * ln(1.25) / (n * ln(10) * ln(n / 0.2)))), 9) AS blanket_r_max,
 ceil(45 * {o.hop_cap("n")} / 0.1 * sqrt(n * deg * ln(1.25) * ln(20) / (0.2 * ln(n / 0.2))))::BIGINT AS blanket_walks,
 round(ln(0.1 * sqrt(0.2 * deg / (n * ln(10)))), 9) AS residue_r_max,
 round(ln(0.01 * (0.2 / n) / (12 * {o.hop_cap("n")})), 9) AS shared_theta,
 ceil((0.2 / 3 + 2) / (0.01 * (0.2 / n)) * ln(10))::BIGINT AS walk_count FROM tg JOIN nd ON node = t, st"""))  # fmt: skip
def method_parameters(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "purchase")
    n, d = g.stats.n, F.col("deg")
    ln = lambda c: F.round(F.log(c), 9)
    return uniform_targets(g, 10).join(g.nodes.select(F.col("node").alias("t"), "deg"), "t").select(
        "t", "deg", ln(F.lit(pm.push_eps(n, P))).alias("push_eps"), ln(pm.blanket_r_max(d, n, P)).alias("blanket_r_max"),
        pm.blanket_walks(d, n, P).cast("long").alias("blanket_walks"), ln(pm.residue_r_max(d, n, P)).alias("residue_r_max"),
        ln(F.lit(pm.shared_theta(n, P))).alias("shared_theta"), F.lit(pm.walk_count(P, P.alpha / n)).cast("long").alias("walk_count"),
    )


_SUB = "least(pow(m::DOUBLE * m * max_deg / pow(2.0 * m / n, 2), 1.0 / 3), pow(pow(m::DOUBLE, 4) / pow(2.0 * m / n, 3), 0.2))"


@register("complexity_table", o.query("supply", targets=o.uniform(10), final=f"""SELECT qid, t, deg, method, round(complexity, 4) AS complexity, round(complexity / least(deg, sqrt(m)), 6) AS improvement
 FROM (SELECT qid, t, deg, m, unnest(['adaptive_push', 'power_iteration', 'walk_sample', 'reverse_push', 'reverse_push_priority', 'blanket_bidirectional', 'residue_bidirectional', 'randomized_reverse_push', 'subgraph_walks']) AS method,
  unnest([least(deg, sqrt(m)), m, n, n * deg, least(n * deg, m), sqrt(n * deg), sqrt(n * deg), n, {_SUB}]::DOUBLE[]) AS complexity FROM tg JOIN nd ON node = t, st)"""))  # fmt: skip
def complexity_table(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "supply")
    return acc.complexity_table(g, uniform_targets(g, 10), P).select("qid", "t", "deg", "method", F.round("complexity", 4).alias("complexity"), r6("improvement").alias("improvement"))


@register("theta_from_pagerank", o.query("supply", o.power(10), final=f"""SELECT nd.node, deg, round(ln(0.01 * 0.1 * n * pi / (4 * {o.hop_cap("n")} * deg)), 9) AS theta
 FROM nd JOIN pw ON pw.node = nd.node AND i = 10, st"""))  # fmt: skip
def theta_from_pagerank(spark: SparkSession, sf: str) -> DataFrame:
    """The theta that a known PageRank would allow, for every node."""
    g = gr.graph(spark, sf, "supply")
    known = g.nodes.select("node", "deg").join(ex.power_iteration(g, P, 10), "node")
    return known.select("node", "deg", F.round(F.log(pm.theta_oracle(F.col("deg"), F.col("pi"), g.stats.n, P)), 9).alias("theta"))


@register("failure_rate_sampled", o.query("tree", o.push("0.05", 12, reps=20), o.series(o.UNIFORM_START, "", 0.8, [0.2] * 13), targets=o.uniform(5), final="""SELECT qid, t,
 avg((abs(pagerank - value) > 0.5 * value)::INT)::DOUBLE AS failure_rate, round(avg(abs(pagerank - value) / value), 6) AS mean_error, count(*) AS replicas FROM pe JOIN sv ON sv.node = pe.t GROUP BY qid, t"""))  # fmt: skip
def failure_rate_sampled(spark: SparkSession, sf: str) -> DataFrame:
    """Replicas of the sampled method that err by more than c = 0.5, against the exact value over as many hops."""
    g = gr.graph(spark, sf, "tree")
    est = adaptive_push(g, uniform_targets(g, 5), P, theta=0.05, hops=12, sampler="edge", coin="md5", reps=20).df
    rows = acc.relative_error(est, ex.truncated_pagerank(g, P, 12))
    return rows.groupBy("qid", "t").agg(F.avg((F.col("rel") > 0.5).cast("double")).alias("failure_rate"), r6(F.avg("rel")).alias("mean_error"), F.count("*").alias("replicas"))


@register("estimate_sink", o.query("tree", o.push("0.01", H), targets=o.uniform(5), final="SELECT 'first' AS run, " + _EST.removeprefix("SELECT ")))
def estimate_sink(spark: SparkSession, sf: str) -> DataFrame:
    """Estimates written by method and read back."""
    import uuid

    from nodeflux.plans.storage import shared_dir
    from nodeflux.sources.sinks import read_estimates, write_estimates

    g, path = gr.graph(spark, sf, "tree"), f"{shared_dir(spark)}/estimates-{uuid.uuid4().hex}"
    write_estimates(adaptive_push(g, uniform_targets(g, 5), P, theta=0.01, hops=H, sampler="edge", coin="md5").df, path, "first")
    back = read_estimates(spark, path, "adaptive_push")
    return back.select("run", "qid", "t", npi(g), "increments", "exact_increments")


@register("lower_bounds", o.query("supply", final="""SELECT node, deg, 0.2::DOUBLE AS by_teleport, round(0.2 * (1 + 0.8 * deg * deg / (2 * m)), 6) AS by_degree,
 round(deg * 0.2 * sqrt(1.6 / m), 6) AS by_edges FROM nd, st"""))  # fmt: skip
def lower_bounds(spark: SparkSession, sf: str) -> DataFrame:
    return ex.lower_bounds(gr.graph(spark, sf, "supply"), P).select("node", "deg", "by_teleport", r6("by_degree").alias("by_degree"), r6("by_edges").alias("by_edges"))


@register("cost_bounds", o.query("supply", targets=o.uniform(10), final=f"""SELECT qid, t, deg, round(ln({o.theta_auto("n", "m", "deg")}), 9) AS theta, round(ln(0.8 / (0.2 * {o.theta_auto("n", "m", "deg")})), 9) AS increment_bound,
 round(ln(12 * {o.hop_cap("n")} / 0.0004 * least(deg, sqrt(m / 1.6))), 9) AS cost_bound FROM tg JOIN nd ON node = t, st"""))  # fmt: skip
def cost_bounds(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "supply")
    ln = lambda c: F.round(F.log(c), 9).alias(c)
    return acc.bounds_table(g, uniform_targets(g, 10), P).select("qid", "t", "deg", ln("theta"), ln("increment_bound"), ln("cost_bound"))


@register("relative_error_report", o.query("tree", o.push("0.0", H), o.power(10), targets=o.uniform(10), final="""SELECT round(avg(rel), 6) AS mean_error_over_c, round(max(rel), 6) AS max_error_over_c,
 avg((rel > 1)::INT)::DOUBLE AS failure_rate, count(*) AS queries, method FROM (SELECT 'adaptive_push' AS method, abs(pagerank - pi) / pi / 0.1 AS rel FROM pe JOIN pw ON t = node AND i = 10) GROUP BY ROLLUP (method)"""))  # fmt: skip
def relative_error_report(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    est = adaptive_push(g, uniform_targets(g, 10), P, theta=0.0, hops=H, sampler="edge").df
    rows = acc.error_report(acc.relative_error(est, ex.power_iteration(g, P, 10)), P, ["method"])
    return rows.select("method", r6("mean_error_over_c").alias("mean_error_over_c"), r6("max_error_over_c").alias("max_error_over_c"), "failure_rate", "queries")


@register("variance_ratio", o.query("tree", o.push("0.02", 4, reps=8), o.power(8), targets=o.uniform(5), final="""SELECT qid, t, round(var_samp(pagerank) * 1e9, 6) AS variance,
 round(var_samp(pagerank) / (4 * 0.02 * any_value(deg) / any_value(n) * any_value(pi)), 6) AS ratio FROM pe JOIN pw ON t = pw.node AND i = 8 JOIN nd ON nd.node = t, st GROUP BY qid, t"""))  # fmt: skip
def variance_ratio(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    est = adaptive_push(g, uniform_targets(g, 5), P, theta=0.02, hops=4, sampler="edge", coin="md5", reps=8).df
    return acc.variance_ratio(g, est, ex.power_iteration(g, P, 8), P, 4).select("qid", "t", r6(F.col("variance") * 1e9).alias("variance"), r6("ratio").alias("ratio"))


@register("hop_variance", o.query("supply", f"""hv AS (SELECT qid, dst AS node, sum(greatest(0.8 / src_deg, 0.05)) AS s, sum(pow(greatest(0.8 / src_deg, 0.05), 2)) AS ss
 FROM tg JOIN e ON src = t, (SELECT unnest(range(40)) AS rep) WHERE 0.8 / src_deg >= 0.05 OR {o.duck_u01("0", "qid", "rep", "0", "src", "dst")} < 0.8 / src_deg / 0.05 GROUP BY qid, dst)""",
    targets=o.uniform(3), final="SELECT qid, node, round(greatest((ss / 40 - pow(s / 40, 2)) * 40 / 39, 0.0), 9) + 0.0 AS variance, round(0.05 * s / 40, 9) AS bound FROM hv"))
def hop_variance(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "supply")
    t = uniform_targets(g, 3).join(g.nodes.select(F.col("node").alias("t"), "deg"), "t")
    residue = t.select("qid", F.lit(0).alias("rep"), F.lit(0.05).alias("theta"), F.col("deg").alias("t_deg"), F.col("t").alias("node"), "deg", F.lit(1.0).alias("r"))
    return acc.hop_variance(g, residue, P, 0, 40, coin="md5").select("qid", "node", (F.round(F.greatest("variance", F.lit(0.0)), 9) + 0.0).alias("variance"), F.round("bound", 9).alias("bound"))


@register("truncation_gap", o.query("tree", o.power(12), o.series(o.UNIFORM_START, "", 0.8, _TRUNC), final="SELECT round(min(pi - value) * any_value(n), 6) AS least, round(max(pi - value) * any_value(n), 6) AS most FROM pw JOIN sv ON pw.node = sv.node AND i = 12, st"))
def truncation_gap(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    gap = acc.truncation_gap(ex.power_iteration(g, P, 12), ex.truncated_pagerank(g, P, H))
    return gap.select(r6(F.col("least") * g.stats.n).alias("least"), r6(F.col("most") * g.stats.n).alias("most"))


@register("reserve_gap", o.query("tree", o.ADJ, o.reverse("0.013", 4), o.series(o.ONE_HOT, "qid", 0.8, _TRUNC), targets=o.uniform(5), final="""SELECT qid, round(min(gap), 6) AS least, round(max(gap), 6) AS most FROM (
 SELECT coalesce(x.qid, y.qid) AS qid, coalesce(x.v, 0) - coalesce(y.p, 0) AS gap FROM (SELECT qid, sv.node, value * a.deg / b.deg AS v FROM sv JOIN tg USING (qid) JOIN nd a ON a.node = tg.t JOIN nd b ON b.node = sv.node) x
 FULL JOIN (SELECT qid, node, p FROM rv WHERE round = 4) y ON x.qid = y.qid AND x.node = y.node) GROUP BY qid"""))  # fmt: skip
def reserve_gap(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    t = uniform_targets(g, 5)
    return acc.reserve_gap(ex.ppr_to(g, t, P, H), rv.reverse_push(g, t, P, 0.013, rounds=4)).select("qid", r6("least").alias("least"), r6("most").alias("most"))


@register("recurrence_gap", o.query("tree", o.power(8), final="""SELECT round(max(abs(a.pi - b.pi)) * any_value(n), 6) AS gap FROM pw a JOIN pw b ON a.node = b.node AND a.i = 7 AND b.i = 8, st"""))
def recurrence_gap(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    return ex.recurrence_gap(g, ex.power_iteration(g, P, 7), P).select(r6(F.col("gap") * g.stats.n).alias("gap"))


_FLOWS = """fl AS MATERIALIZED (SELECT {hop}a.qid, b.qid AS other, {value} * deg AS flow FROM tg a JOIN {table} v ON v.qid = a.qid JOIN tg b ON v.node = b.t JOIN nd ON nd.node = a.t)"""


@register("reversibility_gap", o.query("supply", o.series(o.ONE_HOT, "qid", 0.8, _TRUNC[:5]), _FLOWS.format(hop="", value="v.value", table="sv"), targets=o.uniform(6),
    final="SELECT x.qid, x.other, round(abs(x.flow - y.flow), 9) AS gap FROM fl x JOIN fl y ON x.qid = y.other AND x.other = y.qid WHERE x.qid < x.other"))
def reversibility_gap(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "supply")
    t = uniform_targets(g, 6)
    return ex.reversibility_gap(g, ex.ppr_from(g, t, P, 4), t).select("qid", "other", F.round("gap", 9).alias("gap"))


@register("reversibility_by_hop", o.query("supply", o.series(o.ONE_HOT, "qid", 0.8, _TRUNC[:5]), _FLOWS.format(hop="v.hop, ", value="0.2 * v.r", table="rr"), targets=o.uniform(6),
    final="SELECT x.hop, x.qid, x.other, round(x.flow, 9) AS flow, round(abs(x.flow - y.flow), 9) AS gap FROM fl x JOIN fl y ON x.hop = y.hop AND x.qid = y.other AND x.other = y.qid WHERE x.qid < x.other AND x.hop BETWEEN 1 AND 4"))
def reversibility_by_hop(spark: SparkSession, sf: str) -> DataFrame:
    """Both ways of a pair of targets agree hop by hop once each is weighted by its sender's degree."""
    g = gr.graph(spark, sf, "supply")
    t, out = uniform_targets(g, 6), None
    deg = t.join(g.nodes.select(F.col("node").alias("t"), "deg"), "t")
    for hop in range(1, 5):
        vec = ex.hop_ppr(g, t, hop, P)
        flow = vec.join(deg.select("qid", "deg"), "qid").join(t.select(F.col("qid").alias("other"), F.col("t").alias("node")), "node")
        flow = flow.select("qid", "other", F.round(F.col("value") * F.col("deg"), 9).alias("flow"))
        part = ex.reversibility_gap(g, vec, t).join(flow, ["qid", "other"])
        part = part.select(F.lit(hop).alias("hop"), "qid", "other", "flow", F.round("gap", 9).alias("gap"))
        out = part if out is None else out.unionByName(part)
    return out


@register("convergence_rate", o.query("tree", o.power(6), """ch AS (SELECT b.i AS iteration, max(abs(a.pi - b.pi)) AS change FROM pw a JOIN pw b ON a.node = b.node AND b.i = a.i + 1 GROUP BY b.i)""",
    final="SELECT iteration, round(change * n, 6) AS change, round(change / lag(change) OVER (ORDER BY iteration), 6) AS ratio FROM ch, st"))
def convergence_rate(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    return ex.convergence(g, P, 6).select("iteration", r6(F.col("change") * g.stats.n).alias("change"), r6("ratio").alias("ratio"))


@register("tail_exponent", o.query("terms", final="SELECT round(1 + 1 / avg(ln(deg / 10.0)), 6) AS exponent, count(*) AS tail FROM nd WHERE deg >= 10"))
def tail_exponent(spark: SparkSession, sf: str) -> DataFrame:
    return acc.tail_exponent(gr.graph(spark, sf, "terms").nodes, "deg", 10.0).select(r6("exponent").alias("exponent"), "tail")


@register("sweep_cut", o.query("links", o.series(o.ONE_HOT, "qid", 0.8, _TRUNC[:5]), """rk AS MATERIALIZED (SELECT qid, sv.node, deg, row_number() OVER (PARTITION BY qid ORDER BY round(value / deg, 12) DESC, sv.node) AS rank FROM sv JOIN nd ON nd.node = sv.node),
cl AS (SELECT x.qid, x.rank, 2 * count(*) AS closed FROM rk x JOIN e ON x.node = src JOIN rk y ON y.node = dst AND y.qid = x.qid AND y.rank < x.rank GROUP BY ALL),
gw AS (SELECT rk.qid, rk.rank AS size, sum(deg) OVER w AS volume, sum(deg) OVER w - sum(coalesce(closed, 0)) OVER w AS cut FROM rk LEFT JOIN cl ON rk.qid = cl.qid AND rk.rank = cl.rank WINDOW w AS (PARTITION BY rk.qid ORDER BY rk.rank ROWS UNBOUNDED PRECEDING)),
cd AS (SELECT *, cut / least(volume, 2 * m - volume) AS conductance FROM gw, st WHERE least(volume, 2 * m - volume) > 0)""", targets=o.uniform(5),
    final="SELECT qid, size, volume::BIGINT AS volume, cut::BIGINT AS cut, round(conductance, 6) AS conductance FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY conductance, size) AS r FROM cd) WHERE r = 1"))
def sweep_cut(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "links")
    got = acc.sweep_cut(g, ex.ppr_from(g, uniform_targets(g, 5), P, 4))
    return got.select("qid", F.col("size").cast("long").alias("size"), "volume", "cut", r6("conductance").alias("conductance"))


# -- query sets and workloads --------------------------------------------------------------------------

@register("uniform_targets", o.query("purchase", targets=o.uniform(10), final="SELECT qid, t FROM tg"))
def uniform_query(spark: SparkSession, sf: str) -> DataFrame:
    return uniform_targets(gr.graph(spark, sf, "purchase"), 10)


@register("degree_targets", o.query("terms", targets=o.by_degree(10), final="SELECT qid, t FROM tg"))
def degree_query(spark: SparkSession, sf: str) -> DataFrame:
    return degree_targets(gr.graph(spark, sf, "terms"), 10)


@register("stratified_targets", o.query("terms", final=o.strata(5)))
def stratified_query(spark: SparkSession, sf: str) -> DataFrame:
    return stratified_targets(gr.graph(spark, sf, "terms"), 5)


@register("pagerank_topk", o.query("links", o.power(10), final="SELECT node, round(pi * n, 6) AS n_pi FROM pw, st WHERE i = 10 ORDER BY round(pi, 12) DESC, node LIMIT 10"))
def pagerank_topk(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "links")
    return ex.power_iteration(g, P, 10).orderBy(F.desc(F.round("pi", 12)), "node").limit(10).select("node", npi(g, "pi"))


@register("ppr_topk", o.query("purchase", o.series(o.ONE_HOT, "qid", 0.8, _TRUNC[:4]), targets=o.uniform(5), final="""SELECT qid, node, rank FROM (
 SELECT qid, node, row_number() OVER (PARTITION BY qid ORDER BY round(value, 10) DESC, node) AS rank FROM sv) WHERE rank <= 10"""))  # fmt: skip
def ppr_topk(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "purchase")
    rank = F.row_number().over(Window.partitionBy("qid").orderBy(F.desc(F.round("value", 10)), "node"))
    return ex.ppr_from(g, uniform_targets(g, 5), P, 3).withColumn("rank", rank).filter("rank <= 10").select("qid", "node", F.col("rank").cast("long").alias("rank"))


@register("watch_list", o.query("links", o.power(10), final="SELECT row_number() OVER (ORDER BY round(pi, 12) DESC, node) - 1 AS qid, node AS t FROM pw WHERE i = 10 ORDER BY round(pi, 12) DESC, node LIMIT 10"))
def watch_list(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "links")
    return wl.watch_list(g, 10, P, ex.power_iteration(g, P, 10)).withColumn("qid", F.col("qid").cast("long"))


for _label, _kind, _c in (("uniform_tight", "uniform", 0.1), ("uniform_loose", "uniform", 0.5), ("degree_tight", "degree", 0.1), ("degree_loose", "degree", 0.5)):

    @register(f"workload_{_label}")
    def _workload(spark: SparkSession, sf: str, kind: str = _kind, c: float = _c) -> DataFrame:
        return wl.summary(wl.run_query_set(spark, sf, ["supply", "links"], wl.METHODS, kind, P.but(c=c)))


@register("workload_strata")
def workload_strata(spark: SparkSession, sf: str) -> DataFrame:
    return wl.summary(wl.run_query_set(spark, sf, ["supply", "links", "chat"], wl.METHODS, "strata", P, k=5))


@register("workload_error", " UNION ALL ".join(f"""SELECT * FROM ({o.query(name, o.places(o.theta_auto("n", "m", "deg"), o.WHOLE), o.power(100), targets=o.uniform(10),
    final=f"SELECT '{name}' AS graph, 'adaptive_push' AS method, round(avg(increments), 3) AS mean_increments, round(avg(draws), 3) AS mean_draws, round(avg(abs(pagerank - pi) / pi / 0.1), 6) AS mean_error_over_c, round(max(abs(pagerank - pi) / pi / 0.1), 6) AS max_error_over_c, count(*) AS queries FROM pe JOIN pw ON t = node AND i = 100")})""" for name in ("tree", "links")))  # fmt: skip
def workload_error(spark: SparkSession, sf: str) -> DataFrame:
    """Costs and errors of the method's own schedule against 100 power iterations; draws that SQL repeats."""
    rows = wl.run_query_set(spark, sf, ["tree", "links"], ("adaptive_push",), "uniform", P, coin="md5")
    mean = lambda c, k: F.round(F.avg(c), k)
    return rows.groupBy("graph", "method").agg(
        mean("increments", 3).alias("mean_increments"), mean("draws", 3).alias("mean_draws"), mean("error_over_c", 6).alias("mean_error_over_c"),
        r6(F.max("error_over_c")).alias("max_error_over_c"), F.count("*").alias("queries"),
    )


@register("workload_error_dense")
def workload_error_dense(spark: SparkSession, sf: str) -> DataFrame:
    return wl.summary(wl.run_query_set(spark, sf, ["purchase", "supply"], ("adaptive_push",), "uniform", P))


@register("workload_error_by_degree")
def workload_error_by_degree(spark: SparkSession, sf: str) -> DataFrame:
    """The same measure where targets are drawn by degree."""
    return wl.summary(wl.run_query_set(spark, sf, ["purchase", "supply", "tree", "links"], ("adaptive_push",), "degree", P))


@register("workload_growth")
def workload_growth(spark: SparkSession, sf: str) -> DataFrame:
    return wl.cost_vs_degree(wl.run_query_set(spark, sf, ["supply", "links", "chat"], wl.METHODS, "strata", P, k=5))


@register("workload_methods_by_graph", " UNION ALL ".join(f"""SELECT * FROM ({o.query(name, o.ADJ, o.places(o.theta_auto("n", "m", "deg", 0.5), o.WHOLE_LOOSE), o.reverse("0.1 / n", 80), targets=o.uniform(10),
    final=f"SELECT '{name}' AS graph, (SELECT round(avg(increments), 3) FROM pe) AS adaptive_push, (SELECT sum(touched) / 10.0 FROM rv WHERE round = 80) AS reverse_push, 200.0::DOUBLE * m AS power_iteration FROM st")})""" for name in ("tree", "links")))  # fmt: skip
def workload_methods_by_graph(spark: SparkSession, sf: str) -> DataFrame:
    methods = ("adaptive_push", "reverse_push", "power_iteration")
    return wl.method_by_graph(wl.run_query_set(spark, sf, ["tree", "links"], methods, "uniform", P.but(c=0.5), coin="md5"), methods)


def _contrast(draw: str, column: str) -> str:
    return f"{column} AS (SELECT qid, t, var_samp(pi) AS v FROM (SELECT qid, t, rep, sum(0.2 * r) / any_value(n) AS pi FROM rz_{draw} JOIN tg USING (qid), st GROUP BY ALL) GROUP BY qid, t)"


@register("draw_contrast", o.query("tree", *[o.randomized(5.0123e-3, 8, d == "edge", reps=30).replace("rz", f"rz_{d}") for d in ("shared", "edge")], _contrast("shared", "one"), _contrast("edge", "own"),
    targets=o.uniform(5), final="SELECT qid, t, round(one.v * 1e9, 6) AS shared, round(own.v * 1e9, 6) AS apart FROM one JOIN own USING (qid, t)"))
def draw_contrast(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "tree")
    got = wl.draw_contrast(g, uniform_targets(g, 5), P, 5.0123e-3, 30, 8, coin="md5")
    return got.select("qid", "t", r6(F.col("shared") * 1e9).alias("shared"), r6(F.col("apart") * 1e9).alias("apart"))


_HUB = "tg AS MATERIALIZED (SELECT 0 AS qid, 0 AS t)"


@register("draw_contrast_star", " UNION ALL ".join(f"""SELECT * FROM ({o.query("star", o.randomized(1.5, 2, d == "edge", reps=40), targets=_HUB,
    final=f"SELECT '{d}' AS draw, round(var_samp(pi) * 1e6, 4) AS variance, round(avg(pi) * 401, 4) AS n_pi FROM (SELECT rep, sum(0.2 * r) / any_value(n) AS pi FROM rz, st GROUP BY rep)")})""" for d in ("shared", "edge")))  # fmt: skip
def draw_contrast_star(spark: SparkSession, sf: str) -> DataFrame:
    """A hub whose push pays all leaves by one draw, or each leaf by its own: the variance of its PageRank."""
    g, out = gr.graph(spark, sf, "star"), None
    hub = spark.createDataFrame([(0, 0)], "qid int, t long")
    for draw in ("shared", "edge"):
        rows = rv.randomized_reverse_push(g, hub, P, 1.5, draw, 2, reps=40, coin="md5")
        part = rows.agg(F.lit(draw).alias("draw"), F.round(F.var_samp("pagerank") * 1e6, 4).alias("variance"), F.round(F.avg("pagerank") * g.stats.n, 4).alias("n_pi"))
        out = part if out is None else out.unionByName(part)
    return out


_SWEEP = "SELECT {head}, round(avg(increments), 3) AS mean_increments, round(avg(abs(pagerank - pi) / pi) / {c}, 6) AS {error} FROM pe JOIN pw ON t = node AND i = 100"


@register("theta_sweep", " UNION ALL ".join(f"""SELECT * FROM ({o.query("supply", o.places(repr(x), o.WHOLE, reps=5), o.power(100), targets=o.uniform(5),
    final=_SWEEP.format(head=f"{x!r}::DOUBLE AS theta", c="1", error="mean_error"))})""" for x in (1e-4, 1e-3, 1e-2)))  # fmt: skip
def theta_sweep(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "supply")
    rows = wl.sweep(g, uniform_targets(g, 5), [1e-4, 1e-3, 1e-2], P, 5, coin="md5")
    return rows.select("theta", F.round("mean_increments", 3).alias("mean_increments"), r6("mean_error").alias("mean_error"))


_GRID = [(a, c) for a in (0.1, 0.2, 0.5) for c in (0.1, 0.5)]


@register("parameter_sweep", " UNION ALL ".join(f"""SELECT * FROM ({o.query("links", o.places(o.theta_auto("n", "m", "deg", c, a=a), f"(SELECT {o.hop_cap('n', c, a)} FROM st)", a=a), o.power(100, a), targets=o.uniform(5),
    final=_SWEEP.format(head=f"{a!r}::DOUBLE AS alpha, {c!r}::DOUBLE AS c, 0.1::DOUBLE AS pf", c=repr(c), error="mean_error_over_c"))})""" for a, c in _GRID))  # fmt: skip
def parameter_sweep(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "links")
    rows = wl.parameter_sweep(g, uniform_targets(g, 5), [Params(a, c) for a, c in _GRID], coin="md5")
    return rows.select("alpha", "c", "pf", F.round("mean_increments", 3).alias("mean_increments"), r6("mean_error_over_c").alias("mean_error_over_c"))


@register("udaf_median_of_means", o.query("tree", o.push("0.0193", H, reps=9), targets=o.uniform(5), final="""SELECT qid, t, round(quantile_cont(mean, 0.5) * any_value(n), 6) AS n_pi FROM (
 SELECT qid, t, avg(pagerank) AS mean FROM pe GROUP BY qid, t, rep % 3), st GROUP BY qid, t"""))  # fmt: skip
def udaf_median_of_means(spark: SparkSession, sf: str) -> DataFrame:
    """The aggregate function of SQL users over nine replicas in three groups."""
    from nodeflux.functions import udaf

    udaf.register(spark)
    g = gr.graph(spark, sf, "tree")
    est = adaptive_push(g, uniform_targets(g, 5), P, theta=0.0193, hops=H, sampler="edge", coin="md5", reps=9).df
    est.createOrReplaceTempView("replicas")
    return spark.sql("SELECT qid, t, median_of_means(pagerank, rep, 3) AS pagerank FROM replicas GROUP BY qid, t").select("qid", "t", npi(g))


_NUMBERED = "SELECT row_number() OVER (ORDER BY k) - 1 AS i, count(*) OVER () AS n FROM (SELECT DISTINCT {key} AS k FROM {table} WHERE {key} IS NOT NULL)"


@register("synthetic_shapes", f"""WITH c AS MATERIALIZED ({_NUMBERED.format(key="c_custkey", table="customer")}), k AS MATERIALIZED ({_NUMBERED.format(key="n_nationkey", table="nation")})
 SELECT 'star' AS shape, i AS a, 0 AS b FROM c WHERE i > 0 UNION ALL SELECT 'complete', x.i, y.i FROM k x JOIN k y ON x.i < y.i
 UNION ALL SELECT 'cycle', i, (i + 1) % n FROM c WHERE n > 2 UNION ALL SELECT 'attached', i, floor(i * u * u)::BIGINT FROM (SELECT i, {o.duck_u01("7", "i")} AS u FROM c WHERE i > 0)""")  # fmt: skip
def synthetic_shapes(spark: SparkSession, sf: str) -> DataFrame:
    """Known shapes whose nodes are the customers; the complete one, of all pairs, is of the nations."""
    from nodeflux.sources import synthetic

    out = None
    for shape, table, key in (("star", "customer", "c_custkey"), ("complete", "nation", "n_nationkey"), ("cycle", "customer", "c_custkey"), ("attached", "customer", "c_custkey")):
        rows = synthetic.over(load(spark, sf, table).select(F.col(key).alias("key")), shape, 7).select(F.lit(shape).alias("shape"), "a", "b")
        out = rows if out is None else out.union(rows)
    return out


@register("stream_watch", o.query("activity", o.push("0.01", 8), targets="tg AS MATERIALIZED (SELECT CASE key WHEN 'u:1' THEN 0 WHEN 'u:2' THEN 1 ELSE 2 END AS qid, node AS t FROM nd WHERE key IN ('u:1', 'u:2', 'u:3'))",
    final="SELECT qid, t, round(pagerank, 9) AS pagerank, increments::BIGINT AS increments FROM pe"))
def stream_watch(spark: SparkSession, sf: str) -> DataFrame:
    """Three users' estimates after the last batch of the stream of events."""
    import uuid

    from nodeflux.plans.storage import cut, shared_dir
    from nodeflux.streaming import activity as st

    held, asked = [], spark.createDataFrame([(i, f"u:{i + 1}") for i in range(3)], "qid int, key string")
    keep = lambda df, number: held.append(cut(df, "watched"))
    st.watch(st.read_events(spark, sf), asked, P, keep, 0.01, f"{shared_dir(spark)}/watch-{uuid.uuid4().hex}", hops=8, sampler="edge", coin="md5").awaitTermination()
    return held[-1].select("qid", "t", F.round("pagerank", 9).alias("pagerank"), "increments")


@register("spark_cost")
def spark_cost(spark: SparkSession, sf: str) -> DataFrame:
    """What the distributed plans cost Spark on one graph, by method."""
    from dataclasses import astuple

    from nodeflux.plans.cost import spark_cost as cost

    g, rows = gr.graph(spark, sf, "tree"), []
    t = uniform_targets(g, 5)
    runs = {
        "adaptive_push": lambda: adaptive_push(g, t, P, theta=1e-2, hops=H).df, "power_iteration": lambda: ex.power_iteration(g, P, 10),
        "reverse_push": lambda: rv.reverse_push(g, t, P, 0.013), "walk_sample": lambda: wk.walk_sample(g, t, P, 2000),
    }
    for name, run in runs.items():
        rows.append((name, *astuple(cost(spark, run))))
    return spark.createDataFrame(rows, "method string, jobs int, stages int, rows_read long, bytes_read long, shuffle_bytes long, spilled_bytes long, cpu_seconds double")


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """The main method at c = 0.1 for ten uniform targets, beside 100 power iterations."""
    g = gr.graph(spark, sf, "purchase")
    est = single_node_pagerank(g, uniform_targets(g, 10), P)
    return acc.relative_error(est, wl.truth(g, P)).select("qid", "t", "pagerank", "truth", "rel", "theta", "increments", "draws", "engine")


QUERIES["flagship"] = flagship


for _engine in ("distributed", "exact"):

    @register(f"engine_{_engine}")
    def _by_engine(spark: SparkSession, sf: str, engine: str = _engine) -> DataFrame:
        g = gr.graph(spark, sf, "links")
        return single_node_pagerank(g, uniform_targets(g, 5), P.but(c=0.5), engine)
