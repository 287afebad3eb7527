"""Graphs that the given tables carry: raw edge tables (a, b) of prefixed keys."""

from __future__ import annotations

import math
import sys
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from nodeflux.plans.storage import cut

from .tables import load


def _key(kind: str, *cols: Column | str) -> Column:
    return F.concat(F.lit(kind + ":"), F.concat_ws("/", *[(F.col(c) if isinstance(c, str) else c).cast("string") for c in cols]))


def _bought(spark: SparkSession, sf: str) -> DataFrame:
    orders = load(spark, sf, "orders").select("o_orderkey", "o_custkey")
    items = load(spark, sf, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    return orders.join(items, F.col("o_orderkey") == F.col("l_orderkey"))


def purchase(spark: SparkSession, sf: str) -> DataFrame:
    return _bought(spark, sf).select(_key("c", "o_custkey").alias("a"), _key("p", "l_partkey").alias("b"))


def supply(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "lineitem").select(_key("p", "l_partkey").alias("a"), _key("s", "l_suppkey").alias("b"))


def custsupp(spark: SparkSession, sf: str) -> DataFrame:
    return _bought(spark, sf).select(_key("c", "o_custkey").alias("a"), _key("s", "l_suppkey").alias("b"))


def tree(spark: SparkSession, sf: str) -> DataFrame:
    parts = [
        load(spark, sf, "customer").select(_key("c", "c_custkey").alias("a"), _key("n", "c_nationkey").alias("b")),
        load(spark, sf, "supplier").select(_key("s", "s_suppkey").alias("a"), _key("n", "s_nationkey").alias("b")),
        load(spark, sf, "nation").select(_key("n", "n_nationkey").alias("a"), _key("r", "n_regionkey").alias("b")),
    ]
    return parts[0].union(parts[1]).union(parts[2])


def order(spark: SparkSession, sf: str) -> DataFrame:
    one = load(spark, sf, "orders").select(_key("c", "o_custkey").alias("a"), _key("o", "o_orderkey").alias("b"))
    two = load(spark, sf, "lineitem").select(_key("o", "l_orderkey").alias("a"), _key("p", "l_partkey").alias("b"))
    return one.union(two)


def session(spark: SparkSession, sf: str) -> DataFrame:
    """Consecutive users in time. Days are ordered by themselves and joined at their ends, so no task sorts all events."""
    events = load(spark, sf, "events").select("ts", "event_id", "user_id", F.to_date("ts").alias("day"))
    inside = Window.partitionBy("day").orderBy("ts", "event_id")
    within = events.withColumn("next", F.lead("user_id").over(inside)).filter("next is not null").select("user_id", "next")
    ends = events.groupBy("day").agg(
        F.min(F.struct("ts", "event_id", "user_id")).alias("first"), F.max(F.struct("ts", "event_id", "user_id")).alias("last")
    )
    # one row a day: a bounded calendar, not the events
    over = Window.orderBy("day")
    across = ends.select(F.col("last.user_id").alias("user_id"), F.lead("first.user_id").over(over).alias("next")).filter("next is not null")
    return within.union(across).select(_key("u", "user_id").alias("a"), _key("u", "next").alias("b"))


def activity(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "events").select(_key("u", "user_id").alias("a"), _key("h", "event_type", F.hour("ts")).alias("b"))


def links(spark: SparkSession, sf: str) -> DataFrame:
    found = F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1)))
    return load(spark, sf, "pages").select("page_id", found.alias("href")).select(_key("g", "page_id").alias("a"), _key("l", "href").alias("b"))


def terms(spark: SparkSession, sf: str) -> DataFrame:
    token = F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))))
    return load(spark, sf, "documents").select("doc_id", token.alias("t")).select(_key("d", "doc_id").alias("a"), _key("t", "t").alias("b"))


def source(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "documents").select(_key("d", "doc_id").alias("a"), _key("s", "source", "lang").alias("b"))


#: Vectors in a block; the exact nearest-neighbour graph compares all blocks with all, so its work grows with the square of the vectors.
KNN_VECTORS = 2_048
#: A product of matrices sums in another order than the score does; what may still be among the best is scored again.
KNN_SLACK = 1e-7


def knn(spark: SparkSession, sf: str, k: int = 5) -> DataFrame:
    """k nearest vectors by cosine, exactly: products of blocks find the candidates, each is scored in the order of its elements."""
    vectors = load(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))
    unit = vectors.select("vec_id", F.transform("v", lambda x: x / norm).alias("v"))
    blocks = math.ceil(vectors.count() / KNN_VECTORS) or 1
    cloudpickle.register_pickle_by_value(sys.modules[__name__])
    packed = unit.repartition(blocks).mapInArrow(_pack, "ids binary, width int, m binary")
    packed = cut(packed, "knn-vectors")
    pairs = packed.repartition(blocks).crossJoin(packed.toDF("o_ids", "o_width", "o_m"))
    limit, own = "spark.sql.execution.arrow.maxRecordsPerBatch", spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set(limit, "8")  # a row is two blocks
    try:
        found = cut(pairs.mapInArrow(_candidates(k, KNN_SLACK), "a long, b long, dot double"), "knn")
    finally:
        spark.conf.set(limit, own)
    score = -F.round("dot", 9)
    nearest = found.groupBy("a").agg(F.slice(F.sort_array(F.collect_list(F.struct(score.isNull().alias("none"), score.alias("d"), "b"))), 1, k).alias("best"))
    return nearest.select("a", F.explode("best").alias("x")).select(_key("v", "a").alias("a"), _key("v", "x.b").alias("b"))


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(vec_id, v) to blocks of one width: ids and a matrix as bytes. A vector without a value somewhere is a row of NaN."""
    import numpy as np

    def block(width: int, rows: list) -> pa.RecordBatch:
        ids = np.array([i for i, _ in rows], np.int64).tobytes()
        m = np.array([v for _, v in rows], np.float64).reshape(len(rows), width).tobytes()
        return pa.RecordBatch.from_arrays([pa.array([ids], pa.binary()), pa.array([width], pa.int32()), pa.array([m], pa.binary())], ["ids", "width", "m"])

    held: dict[int, list] = {}
    for batch in batches:
        for i, v in zip(batch.column("vec_id").to_pylist(), batch.column("v").to_pylist()):
            if i is None:
                continue
            v = [] if v is None else [float("nan")] * len(v) if None in v else v
            rows = held.setdefault(len(v), [])
            rows.append((i, v))
            if len(rows) >= KNN_VECTORS:
                yield block(len(v), held.pop(len(v)))
    for width, rows in held.items():
        yield block(width, rows)


def _candidates(k: int, slack: float):
    """mapInArrow over pairs of blocks: (a, b, dot), all that can be among a's k nearest in those blocks.

    Of equal scores the k least ids count. Pairs without a score (null vectors, other widths) come last, by id.
    """

    def found(ids, m, other, o) -> Iterator[tuple]:
        import numpy as np

        same = ids[:, None] == other[None, :]
        none = np.isnan(m).any(axis=1)[:, None] | np.isnan(o).any(axis=1)[None, :] if m.shape[1] == o.shape[1] > 0 else np.ones_like(same)
        if none.any():
            order = np.argsort(other, kind="stable")
            free = (none & ~same)[:, order]
            i, j = np.nonzero(free & (np.cumsum(free, axis=1) <= k))
            yield ids[i], other[order][j], np.full(len(i), np.nan)
        if none.all():
            return
        dots = np.where(none | same, -np.inf, m @ o.T)
        least = np.partition(dots, -k, axis=1)[:, -k] if dots.shape[1] > k else np.full(len(dots), -np.inf)
        i, j = np.nonzero((dots >= (least - slack)[:, None]) & (dots > -np.inf))
        exact = np.zeros(len(i))
        for d in range(m.shape[1]):
            exact += m[i, d] * o[j, d]
        order = np.lexsort((other[j], -exact, i))
        i, j, exact = i[order], j[order], exact[order]
        first = np.flatnonzero(np.concatenate(([True], (i[1:] != i[:-1]) | (exact[1:] != exact[:-1]))))
        keep = np.arange(len(i)) - np.repeat(first, np.diff(np.append(first, len(i)))) < k if len(i) else np.zeros(0, bool)
        yield ids[i[keep]], other[j[keep]], exact[keep]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for batch in batches:
            for r in batch.to_pylist():
                ids, other = np.frombuffer(r["ids"], np.int64), np.frombuffer(r["o_ids"], np.int64)
                m = np.frombuffer(r["m"], np.float64).reshape(len(ids), r["width"])
                o = np.frombuffer(r["o_m"], np.float64).reshape(len(other), r["o_width"])
                for a, b, dot in found(ids, m, other, o):
                    yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.array(dot, from_pandas=True)], ["a", "b", "dot"])

    return run


def chat(spark: SparkSession, sf: str) -> DataFrame:
    token = F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))))
    return load(spark, sf, "conversations").select("conv_id", token.alias("t")).select(_key("v", "conv_id").alias("a"), _key("t", "t").alias("b"))


def leak(spark: SparkSession, sf: str, run: int = 5) -> DataFrame:
    """Documents and benchmark items that share a run of words."""
    def runs(table: str, key: str) -> DataFrame:
        w = F.regexp_extract_all(F.lower("text"), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))
        base = load(spark, sf, table).select(key, w.alias("w")).filter(F.size("w") >= run)
        at = F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - run + 1), lambda i: F.concat_ws(" ", *[F.element_at(F.col("w"), i + k) for k in range(run)]))))
        return base.select(key, at.alias("run"))

    both = runs("documents", "doc_id").join(runs("benchmark", "item_id"), "run")
    return both.select(_key("d", "doc_id").alias("a"), _key("b", "item_id").alias("b"))


def star(spark: SparkSession, sf: str, leaves: int = 400) -> DataFrame:
    """A synthetic star: one hub and its leaves, whatever the data folder."""
    return spark.range(leaves).select(F.lit("h:0").alias("a"), _key("l", "id").alias("b"))


GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (purchase, supply, custsupp, tree, order, session, activity, links, terms, source, knn, chat, leak, star)
}

_BOUGHT = "orders JOIN lineitem ON o_orderkey = l_orderkey"
_TOKENS = "unnest(list_distinct(regexp_extract_all(lower(text), '[^\\x20\\x09-\\x0D]+')))"
#: The same raw edges in DuckDB's SQL, written apart from the plans above.
DUCK = {
    "purchase": f"SELECT 'c:' || o_custkey AS a, 'p:' || l_partkey AS b FROM {_BOUGHT}",
    "supply": "SELECT 'p:' || l_partkey AS a, 's:' || l_suppkey AS b FROM lineitem",
    "custsupp": f"SELECT 'c:' || o_custkey AS a, 's:' || l_suppkey AS b FROM {_BOUGHT}",
    "tree": "SELECT 'c:' || c_custkey AS a, 'n:' || c_nationkey AS b FROM customer UNION ALL SELECT 's:' || s_suppkey, 'n:' || s_nationkey FROM supplier "
    "UNION ALL SELECT 'n:' || n_nationkey, 'r:' || n_regionkey FROM nation",
    "order": "SELECT 'c:' || o_custkey AS a, 'o:' || o_orderkey AS b FROM orders UNION ALL SELECT 'o:' || l_orderkey, 'p:' || l_partkey FROM lineitem",
    "session": "SELECT 'u:' || user_id AS a, 'u:' || lead(user_id) OVER (ORDER BY ts, event_id) AS b FROM events",
    "activity": "SELECT 'u:' || user_id AS a, 'h:' || event_type || '/' || hour(ts) AS b FROM events",
    "links": "SELECT 'g:' || page_id AS a, 'l:' || href AS b FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS href FROM pages)",
    "terms": f"SELECT 'd:' || doc_id AS a, 't:' || t AS b FROM (SELECT doc_id, {_TOKENS} AS t FROM documents)",
    "source": "SELECT 'd:' || doc_id AS a, 's:' || source || '/' || lang AS b FROM documents",
    "star": "SELECT 'h:0' AS a, 'l:' || i AS b FROM (SELECT unnest(range(400)) AS i)",
    "chat": f"SELECT 'v:' || conv_id AS a, 't:' || t AS b FROM (SELECT conv_id, {_TOKENS} AS t FROM conversations)",
    "knn": "SELECT 'v:' || a AS a, 'v:' || b AS b FROM (SELECT q.vec_id AS a, o.vec_id AS b, row_number() OVER (PARTITION BY q.vec_id "
    "ORDER BY round(list_dot_product(q.v, o.v), 9) DESC, o.vec_id) AS r FROM u q JOIN u o ON q.vec_id <> o.vec_id) WHERE r <= 5",
    "leak": "SELECT 'd:' || doc_id AS a, 'b:' || item_id AS b FROM "
    "(SELECT doc_id, unnest(list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i+4], ' ')))) AS run FROM "
    "(SELECT doc_id, regexp_extract_all(lower(text), '[^\\x20\\x09-\\x0D]+') AS w FROM documents)) JOIN "
    "(SELECT item_id, unnest(list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i+4], ' ')))) AS run FROM "
    "(SELECT item_id, regexp_extract_all(lower(text), '[^\\x20\\x09-\\x0D]+') AS w FROM benchmark)) USING (run)",
}
