"""Queries of the operators around the methods: joins, aggregates, windows, functions, streams."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from nodeflux.operators import graph as gr
from nodeflux.operators import relational as rel
from nodeflux.operators.targets import stratum, uniform_targets
from nodeflux.plans import oracles as o
from nodeflux.queries import register
from nodeflux.sources.tables import from_query, load
from nodeflux.streaming import activity as st

_PER_ORDER = "SELECT o_custkey, round(sum(l_quantity), 4) AS quantity, count(*) AS items FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_custkey"


for _hint in ("merge", "shuffle_hash"):

    @register(f"join_{_hint}", _PER_ORDER)
    def _join(spark: SparkSession, sf: str, hint: str = _hint) -> DataFrame:
        orders, items = load(spark, sf, "orders").select("o_orderkey", "o_custkey"), load(spark, sf, "lineitem").select("l_orderkey", "l_quantity")
        joined = orders.hint(hint).join(items, F.col("o_orderkey") == F.col("l_orderkey"))
        return joined.groupBy("o_custkey").agg(F.round(F.sum("l_quantity"), 4).alias("quantity"), F.count("*").alias("items"))


@register("join_broadcast", o.query("purchase", targets=o.uniform(10), final="SELECT qid, node, key, deg FROM tg JOIN nd ON node = t"))
def join_broadcast(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "purchase")
    return g.nodes.join(F.broadcast(uniform_targets(g, 10)), F.col("node") == F.col("t")).select("qid", "node", "key", "deg")


@register("join_outer", "SELECT coalesce(c_custkey, -1) AS c_custkey, coalesce(s_suppkey, -1) AS s_suppkey, coalesce(c_acctbal, 0) + coalesce(s_acctbal, 0) AS total FROM customer FULL JOIN supplier ON c_custkey = s_suppkey")
def join_outer(spark: SparkSession, sf: str) -> DataFrame:
    both = load(spark, sf, "customer").join(load(spark, sf, "supplier"), F.col("c_custkey") == F.col("s_suppkey"), "full")
    return both.select(*[F.coalesce(c, F.lit(-1)).cast("long").alias(c) for c in ("c_custkey", "s_suppkey")], (F.coalesce("c_acctbal", F.lit(0.0)) + F.coalesce("s_acctbal", F.lit(0.0))).alias("total"))


@register("join_semi", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def join_semi(spark: SparkSession, sf: str) -> DataFrame:
    good = load(spark, sf, "labels").filter("quality = 1").select("doc_id")
    return load(spark, sf, "documents").select("doc_id", "lang").join(good, "doc_id", "left_semi")


@register("join_anti", "SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "documents").select("doc_id", "lang").join(load(spark, sf, "labels").select("doc_id"), "doc_id", "left_anti")


_SESSIONS = """s AS (SELECT user_id, session, min(ts) AS first, max(ts) AS last, count(*) AS events FROM (
 SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS session FROM (
  SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR epoch_us(ts) - epoch_us(lag(ts) OVER w) > 7200000000 THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts))) GROUP BY user_id, session)"""


@register("sessions", f"WITH {_SESSIONS} SELECT user_id, session::BIGINT AS session, strftime(first, '%Y-%m-%d %H:%M:%S') AS first, events FROM s")
def sessions(spark: SparkSession, sf: str) -> DataFrame:
    got = rel.sessions_of(load(spark, sf, "events"), "user_id", "ts", 7200)
    return got.select("user_id", "session", F.date_format("first", "yyyy-MM-dd HH:mm:ss").alias("first"), "events")


@register("join_interval", f"WITH {_SESSIONS} SELECT event_id, session::BIGINT AS session FROM events e JOIN s ON e.user_id = s.user_id AND ts >= first AND ts <= last WHERE event_type = (SELECT min(event_type) FROM events)")
def join_interval(spark: SparkSession, sf: str) -> DataFrame:
    events = load(spark, sf, "events")
    kind = events.agg(F.min("event_type")).first()[0]
    held = rel.sessions_of(events, "user_id", "ts", 7200)
    return events.filter(F.col("event_type") == kind).join(held.drop("events"), "user_id").filter("ts >= first AND ts <= last").select("event_id", "session")


@register("join_asof", """SELECT event_id, coalesce((SELECT max(b.event_id) FROM events b WHERE b.user_id = a.user_id AND b.event_type = k.hi AND b.ts = (
  SELECT max(c.ts) FROM events c WHERE c.user_id = a.user_id AND c.event_type = k.hi AND c.ts <= a.ts)), -1) AS last_other
 FROM events a, (SELECT min(event_type) AS lo, max(event_type) AS hi FROM events) k WHERE a.event_type = k.lo""")  # fmt: skip
def join_asof(spark: SparkSession, sf: str) -> DataFrame:
    events = load(spark, sf, "events").select("event_id", "ts", "user_id", "event_type")
    low, high = events.agg(F.min("event_type"), F.max("event_type")).first()
    # of equal times the largest id counts
    right = events.filter(F.col("event_type") == high).groupBy("user_id", "ts").agg(F.max("event_id").alias("other"))
    return rel.as_of(events.filter(F.col("event_type") == low).select("event_id", "ts", "user_id"), right, "user_id", "ts", "other").select("event_id", F.coalesce("last_other", F.lit(-1)).alias("last_other"))


_CUM = "cu AS (SELECT node, sum(deg) OVER (ORDER BY node ROWS UNBOUNDED PRECEDING) - deg AS lo, sum(deg) OVER (ORDER BY node ROWS UNBOUNDED PRECEDING) AS hi FROM nd)"


@register("join_range", o.query("tree", _CUM, targets=o.uniform(50), final="SELECT qid, x, node FROM (SELECT qid, (qid * 37 + 11)::BIGINT AS x FROM tg) JOIN cu ON x >= lo AND x < hi"))
def join_range(spark: SparkSession, sf: str) -> DataFrame:
    """Places on the line of cumulative degrees, matched to nodes."""
    g = gr.graph(spark, sf, "tree")
    run = Window.partitionBy("part").orderBy("node").rowsBetween(Window.unboundedPreceding, 0)
    parts = g.nodes.withColumn("part", F.floor(F.col("node") / 1000))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = parts.groupBy("part").agg(F.sum("deg").alias("d")).withColumn("base", F.coalesce(F.sum("d").over(before), F.lit(0)))
    cum = parts.withColumn("run", F.sum("deg").over(run)).join(F.broadcast(base.drop("d")), "part")
    ranges = cum.select("node", (F.col("base") + F.col("run") - F.col("deg")).alias("lo"), (F.col("base") + F.col("run")).alias("hi"))
    points = uniform_targets(g, 50).select("qid", (F.col("qid") * 37 + 11).cast("long").alias("x"))
    return rel.range_join(points, ranges, "x", "lo", "hi", 64.0).select("qid", "x", "node")


@register("join_theta", "SELECT r_name, n_name FROM region JOIN nation ON n_regionkey > r_regionkey")
def join_theta(spark: SparkSession, sf: str) -> DataFrame:
    """A nested loop over two tables of fixed size."""
    return load(spark, sf, "nation").join(F.broadcast(load(spark, sf, "region")), F.col("n_regionkey") > F.col("r_regionkey")).select("r_name", "n_name")


@register("edges_from_sql", "SELECT count(*) AS edges, count(DISTINCT a) AS nodes FROM (SELECT DISTINCT 'c:' || o_custkey AS a, 'o:' || o_orderkey AS b FROM orders)")
def edges_from_sql(spark: SparkSession, sf: str) -> DataFrame:
    raw = from_query(spark, "SELECT concat('c:', o_custkey) AS x, concat('o:', o_orderkey) AS y FROM {orders}", "x", "y", orders=load(spark, sf, "orders"))
    return raw.distinct().agg(F.count("*").alias("edges"), F.countDistinct("a").alias("nodes"))


_KEYS = "l_returnflag, l_linestatus"
for _kind, _sql in (("cube", f"CUBE ({_KEYS})"), ("rollup", f"ROLLUP ({_KEYS})"), ("grouping_sets", "GROUPING SETS ((l_returnflag), (l_linestatus), ())")):

    @register(f"agg_{_kind}", f"SELECT {_KEYS}, count(*) AS items, round(sum(l_quantity), 2) AS quantity FROM lineitem GROUP BY {_sql}")
    def _agg(spark: SparkSession, sf: str, kind: str = _kind) -> DataFrame:
        items = load(spark, sf, "lineitem").select("l_returnflag", "l_linestatus", "l_quantity")
        keys = ["l_returnflag", "l_linestatus"]
        grouped = {
            "cube": lambda: items.cube(*keys), "rollup": lambda: items.rollup(*keys),
            "grouping_sets": lambda: items.groupingSets([["l_returnflag"], ["l_linestatus"], []], *keys),
        }[kind]()
        return grouped.agg(F.count("*").alias("items"), F.round(F.sum("l_quantity"), 2).alias("quantity")).select(*keys, "items", "quantity")


@register("agg_distinct", o.query("purchase", final="SELECT b AS part, count(DISTINCT a) AS customers FROM raw GROUP BY b"))
def agg_distinct(spark: SparkSession, sf: str) -> DataFrame:
    return gr.GRAPHS["purchase"](spark, sf).groupBy(F.col("b").alias("part")).agg(F.countDistinct("a").alias("customers"))


@register("agg_approx_distinct")
def agg_approx_distinct(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@register("agg_pivot", "SELECT l_returnflag, count(*) FILTER (WHERE l_linestatus = 'F') AS F, count(*) FILTER (WHERE l_linestatus = 'O') AS O FROM lineitem GROUP BY l_returnflag")
def agg_pivot(spark: SparkSession, sf: str) -> DataFrame:
    got = load(spark, sf, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count()
    return got.select("l_returnflag", *[F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("F", "O")])


@register("window_rank", o.query("source", final="""SELECT node, kind, rank, dense, tile, percent FROM (SELECT node, split_part(key, ':', 1) AS kind, rank() OVER w AS rank, dense_rank() OVER w AS dense,
 ntile(4) OVER (PARTITION BY split_part(key, ':', 1) ORDER BY deg DESC, node) AS tile, round(percent_rank() OVER w, 6) AS percent FROM nd WINDOW w AS (PARTITION BY split_part(key, ':', 1) ORDER BY deg DESC))"""))  # fmt: skip
def window_rank(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("kind").orderBy(F.desc("deg"))
    t = Window.partitionBy("kind").orderBy(F.desc("deg"), "node")
    long = lambda c, n: c.cast("long").alias(n)
    return gr.graph(spark, sf, "source").nodes.select(
        "node", "kind", long(F.rank().over(w), "rank"), long(F.dense_rank().over(w), "dense"), long(F.ntile(4).over(t), "tile"), F.round(F.percent_rank().over(w), 6).alias("percent")
    )


@register("window_running", "SELECT user_id, event_id, sum(1) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)::BIGINT AS nth, coalesce(lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id), -1) AS before FROM events")
def window_running(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    run = w.rowsBetween(Window.unboundedPreceding, 0)
    return load(spark, sf, "events").select("user_id", "event_id", F.sum(F.lit(1)).over(run).alias("nth"), F.coalesce(F.lag("event_id").over(w), F.lit(-1)).alias("before"))


@register("setops", """SELECT 'both' AS part, count(*) AS ids FROM (SELECT doc_id FROM documents INTERSECT SELECT doc_id FROM labels) UNION ALL
 SELECT 'unlabelled', count(*) FROM (SELECT doc_id FROM documents EXCEPT SELECT doc_id FROM labels) UNION ALL
 SELECT 'any', count(*) FROM (SELECT doc_id FROM documents UNION SELECT doc_id FROM labels) UNION ALL
 SELECT 'all', count(*) FROM (SELECT doc_id FROM documents UNION ALL SELECT doc_id FROM labels)""")  # fmt: skip
def setops(spark: SparkSession, sf: str) -> DataFrame:
    d, lab = load(spark, sf, "documents").select("doc_id"), load(spark, sf, "labels").select("doc_id")
    parts = {"both": d.intersect(lab), "unlabelled": d.subtract(lab), "any": d.union(lab).distinct(), "all": d.union(lab)}
    out = None
    for name, part in parts.items():
        row = part.agg(F.lit(name).alias("part"), F.count("*").alias("ids"))
        out = row if out is None else out.union(row)
    return out


@register("strata_of_nodes", o.query("terms", final=f"SELECT {o.STRATUM} AS stratum, count(*) AS nodes FROM nd, (SELECT 2.0 * m / n AS a FROM st) GROUP BY 1"))
def strata_of_nodes(spark: SparkSession, sf: str) -> DataFrame:
    g = gr.graph(spark, sf, "terms")
    return g.nodes.groupBy(stratum(g.stats.avg_deg).alias("stratum")).agg(F.count("*").alias("nodes"))


@register("link_hosts", "SELECT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, count(*) AS pages FROM pages GROUP BY 1")
def link_hosts(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "pages").groupBy(F.parse_url("url", F.lit("HOST")).alias("host")).agg(F.count("*").alias("pages"))


@register("json_props", "SELECT key AS prop, count(*) AS events FROM (SELECT unnest(json_keys(props::JSON)) AS key FROM events) GROUP BY key")
def json_props(spark: SparkSession, sf: str) -> DataFrame:
    keys = F.explode(F.json_object_keys("props"))
    return load(spark, sf, "events").select(keys.alias("prop")).groupBy("prop").agg(F.count("*").alias("events"))


@register("array_functions", o.query("tree", final="SELECT src, list_sum(list(dst_deg))::BIGINT AS around, list_max(list(dst)) AS last, len(list_filter(list(dst_deg), lambda x: x > 1)) AS branching FROM e GROUP BY src"))
def array_functions(spark: SparkSession, sf: str) -> DataFrame:
    adj = gr.block(gr.graph(spark, sf, "tree").edges, 1 << 20)
    return adj.select(
        "src", F.aggregate("nbr_deg", F.lit(0).cast("long"), lambda s, x: s + x).alias("around"), F.array_max("nbr").alias("last"),
        F.size(F.filter("nbr_deg", lambda x: x > 1)).cast("long").alias("branching"),
    )


@register("map_functions", "SELECT user_id, count(DISTINCT event_type) AS kinds, count(*) FILTER (WHERE event_type = (SELECT min(event_type) FROM events)) AS least FROM events GROUP BY user_id")
def map_functions(spark: SparkSession, sf: str) -> DataFrame:
    events = load(spark, sf, "events")
    low = events.agg(F.min("event_type")).first()[0]
    held = events.groupBy("user_id", "event_type").count().groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "count"))).alias("m"))
    return held.select("user_id", F.size(F.map_keys("m")).cast("long").alias("kinds"), F.coalesce(F.element_at("m", low), F.lit(0)).cast("long").alias("least"))


@register("cosine_to_first", "SELECT a.vec_id, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS cos FROM embeddings a, (SELECT embedding FROM embeddings ORDER BY vec_id LIMIT 1) b")
def cosine_to_first(spark: SparkSession, sf: str) -> DataFrame:
    vectors = load(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    first = vectors.orderBy("vec_id").limit(1).select(F.col("v").alias("w"))
    return vectors.crossJoin(F.broadcast(first)).select("vec_id", F.round(rel.cosine(F.col("v"), F.col("w")), 6).alias("cos"))


@register("udtf_skip_positions")
def udtf_skip_positions(spark: SparkSession, sf: str) -> DataFrame:
    from nodeflux.functions import udtf

    udtf.register(spark)
    gr.graph(spark, sf, "tree").nodes.createOrReplaceTempView("skip_nodes")
    return spark.sql("SELECT node, deg, pos FROM skip_nodes, LATERAL skip_positions(CAST(deg AS INT), CAST(0.3 AS DOUBLE), 1, CAST(node AS INT))")


# -- streams, run over all that is there, against the batch text -------------------------------------------

_WINDOW = "strftime(time_bucket(INTERVAL '{w}', ts, TIMESTAMP '1970-01-01'), '%Y-%m-%d %H:%M:%S')"


def _name(kind: str) -> str:
    return f"{kind}_{uuid.uuid4().hex[:8]}"


@register("stream_tumbling", f"SELECT {_WINDOW.format(w='1 hour')} AS start, event_type, count(*) AS events, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def stream_tumbling(spark: SparkSession, sf: str) -> DataFrame:
    got = st.collect_stream(st.tumbling(st.read_events(spark, sf), "1 hour"), "complete", _name("tumbling"))
    return got.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


@register("stream_sliding", """SELECT strftime(start, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS events, round(sum(value), 4) AS total FROM (
 SELECT *, unnest([time_bucket(INTERVAL '6 hours', ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL '6 hours', ts, TIMESTAMP '1970-01-01') - INTERVAL '6 hours']) AS start FROM events) GROUP BY ALL""")  # fmt: skip
def stream_sliding(spark: SparkSession, sf: str) -> DataFrame:
    got = st.collect_stream(st.tumbling(st.read_events(spark, sf), "12 hours", "6 hours"), "complete", _name("sliding"))
    return got.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


@register("stream_sessions", f"WITH {_SESSIONS.replace('> 7200000000', '>= 7200000000')} SELECT strftime(first, '%Y-%m-%d %H:%M:%S') AS start, user_id, events FROM s")
def stream_sessions(spark: SparkSession, sf: str) -> DataFrame:
    got = st.collect_stream(st.sessions(st.read_events(spark, sf), "2 hours"), "complete", _name("sessions"))
    return got.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


@register("stream_edges", "SELECT DISTINCT 'u:' || user_id AS a, 'h:' || event_type || '/' || hour(ts) AS b FROM events")
def stream_edges(spark: SparkSession, sf: str) -> DataFrame:
    return st.collect_stream(st.fresh_edges(st.read_events(spark, sf)), "append", _name("edges"))


@register("stream_degrees", "SELECT user_id, count(*) AS events FROM events GROUP BY user_id")
def stream_degrees(spark: SparkSession, sf: str) -> DataFrame:
    return st.collect_stream(st.degrees(st.read_events(spark, sf)), "complete", _name("degrees"))


@register("stream_static", "SELECT c_mktsegment, count(*) AS events FROM events JOIN customer ON user_id = c_custkey GROUP BY c_mktsegment")
def stream_static(spark: SparkSession, sf: str) -> DataFrame:
    return st.collect_stream(st.stream_static(st.read_events(spark, sf), load(spark, sf, "customer")), "complete", _name("static"))


@register("stream_pairs", """SELECT a.user_id, a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR
 WHERE a.event_type = 'click' AND b.event_type = 'purchase'""")  # fmt: skip
def stream_pairs(spark: SparkSession, sf: str) -> DataFrame:
    events = st.read_events(spark, sf)
    return st.collect_stream(st.stream_pairs(events.filter("event_type = 'click'"), events.filter("event_type = 'purchase'"), "1 HOUR"), "append", _name("pairs"))
