"""The graph handle: normalised, degree-annotated adjacency, its statistics and its store."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from nodeflux.plans.storage import cut, discard, release
from nodeflux.sources.graphs import GRAPHS

from . import lists

#: Neighbours in a row of the blocked adjacency; a hub has many rows.
BLOCK = 1024
#: Neighbours that one task numbers; a hub's list is dealt into ranges of about so many.
CHUNK = 100_000
#: Up to so many nodes (12 bytes each are sent to the tasks) and raw edges, lists are made of packed numbers; beyond, by joins.
PACKED_NODES = 4_000_000
PACKED_ROWS = 80_000_000


@dataclass(frozen=True)
class Stats:
    n: int
    m: int
    max_deg: int

    @property
    def avg_deg(self) -> float:
        return 2 * self.m / self.n if self.n else 0.0


@dataclass
class Graph:
    """edges(src, dst, pos, src_deg, dst_deg) in both directions, nodes(node, key, kind, deg), stats."""

    edges: DataFrame
    nodes: DataFrame
    stats: Stats
    #: blocked adjacency in partitions by bucket of src, and their number, where the graph was opened from a store
    adj: DataFrame | None = None
    buckets: int = 0

    @property
    def spark(self) -> SparkSession:
        return self.nodes.sparkSession

    @property
    def pairs(self) -> DataFrame:
        """(src, dst) of the edges."""
        return self.edges.select("src", "dst")

    def around(self, frontier: DataFrame) -> DataFrame:
        """Edges that hold all of the senders in frontier(node): of a stored graph only their buckets are read.

        The driver sees the frontier's buckets, of which there are at most `buckets`; the frontier has been written.
        """
        if self.adj is None:
            return self.edges
        wanted = frontier.select(bucket_of(F.col("node"), self.buckets).alias("bucket")).distinct().collect()
        return unblock(self.adj.filter(F.col("bucket").isin(sorted(r.bucket for r in wanted))))

    def write(self, path: str, buckets: int = 64) -> None:
        """Adjacency by bucket of src, sorted by (src, block), so that a hop reads the buckets it needs."""
        bucketed(block(self.edges), buckets).write.partitionBy("bucket").parquet(f"{path}/adj")
        self.nodes.write.parquet(f"{path}/nodes")
        self.spark.createDataFrame([(buckets,)], "buckets int").write.parquet(f"{path}/layout")

    @staticmethod
    def open(spark: SparkSession, path: str) -> Graph:
        adj, nodes = spark.read.parquet(f"{path}/adj"), spark.read.parquet(f"{path}/nodes")
        buckets = spark.read.parquet(f"{path}/layout").first()[0]
        return Graph(unblock(adj), nodes, measure(nodes), adj, buckets)


@dataclass
class Listed(Graph):
    """A graph held as lists, one row a range of nodes; its edges are written as rows when they are first asked for."""

    lists: DataFrame | None = None
    #: edge rows before those of each range
    offsets: tuple[int, ...] = ()

    @property
    def pairs(self) -> DataFrame:
        if self._edges is not None:
            return self._edges.select("src", "dst")
        lists.by_value()
        return self.lists.select("first", "deg", "nbr").mapInArrow(lists.edges(), "src long, dst long")

    def _as_rows(self) -> DataFrame:
        if self._edges is None:
            lists.by_value()
            deg = np.zeros(self.stats.n, np.int32)
            for first, part in self.lists.select("first", "deg").toLocalIterator():
                part = np.frombuffer(part, np.int32)
                deg[first : first + len(part)] = part
            shared = self.spark.sparkContext.broadcast(deg)
            rows = self.lists.select("first", "deg", "nbr").mapInArrow(lists.edges(shared), "src long, dst long, pos int, src_deg long, dst_deg long")
            self._edges = cut(rows, "edges")
            shared.destroy()
        return self._edges


Listed.edges = property(Listed._as_rows, lambda self, rows: setattr(self, "_edges", rows))


def normalise(raw: DataFrame) -> DataFrame:
    """(a, b) in both directions, each pair once; null ends and loops go."""
    clean = raw.select("a", "b").filter("a is not null and b is not null and a <> b")
    return clean.union(clean.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct()


def dense_ids(keys: DataFrame) -> DataFrame:
    """(node, key) numbered 0 .. n - 1 in key order: offsets of range partitions and places inside them.

    The driver sees one row a partition, and no task sees all keys.
    """
    return _numbered(keys.select("key").distinct())


def _numbered(rows: DataFrame) -> DataFrame:
    """rows(key, ...) of different keys with their `node` by key order."""
    spark = rows.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    placed = cut(rows.repartitionByRange(n, "key").sortWithinPartitions("key").withColumn("at", F.monotonically_increasing_id()), "ids")
    part = F.shiftright("at", 33)
    counts = sorted(placed.groupBy(part.alias("part")).count().collect())
    total, firsts = 0, []
    for p, c in counts:
        firsts.append((p, total))
        total += c
    offsets = spark.createDataFrame(firsts, "part long, first long")
    return placed.withColumn("part", part).join(F.broadcast(offsets), "part").select(
        (F.col("first") + F.col("at").bitwiseAND(F.lit((1 << 33) - 1))).alias("node"), *rows.columns
    )


def with_pos(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """edges from (src, dst): degrees of both ends, and pos, the place in the sender's list ordered by dst.

    A hub's list is numbered in ranges of dst; range offsets are added afterwards.
    """
    width = F.greatest(F.lit(1), F.ceil(F.col("src_deg") / CHUNK))
    deg = nodes.select("node", "deg")
    sized = pairs.join(deg.toDF("src", "src_deg"), "src").join(deg.toDF("dst", "dst_deg"), "dst")
    top = nodes.agg(F.max("node").alias("top"))
    ranged = sized.crossJoin(F.broadcast(top)).withColumn("chunk", F.floor(F.col("dst") * width / (F.col("top") + 1))).drop("top")
    counts = ranged.groupBy("src", "chunk").agg(F.count("*").alias("held"))
    before = Window.partitionBy("src").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("src", "chunk", F.coalesce(F.sum("held").over(before), F.lit(0)).alias("first"))
    inside = Window.partitionBy("src", "chunk").orderBy("dst")
    return ranged.withColumn("nth", F.row_number().over(inside)).join(offsets, ["src", "chunk"]).select(
        "src", "dst", (F.col("first") + F.col("nth")).cast("int").alias("pos"), "src_deg", "dst_deg"
    )


def measure(nodes: DataFrame) -> Stats:
    row = nodes.agg(F.count("*"), F.coalesce(F.sum("deg"), F.lit(0)), F.coalesce(F.max("deg"), F.lit(0))).first()
    return Stats(row[0], row[1] // 2, row[2])


def build(raw: DataFrame, isolated: DataFrame | None = None) -> Graph:
    """A graph from raw edges (a, b). isolated (key) adds nodes without edges ("absorb"); else there are none."""
    clean = cut(raw.select("a", "b").filter("a is not null and b is not null and a <> b"), "raw")
    ends = clean.select(F.col("a").alias("key")).union(clean.select("b")).groupBy("key").agg(F.count("*").alias("ends"))
    if isolated is not None:
        lone = isolated.select("key").filter("key is not null").distinct().withColumn("ends", F.lit(0).cast("long"))
        ends = ends.union(lone).groupBy("key").agg(F.sum("ends").alias("ends"))
    keys = _numbered(ends)
    n, rows = keys.agg(F.count("*"), F.coalesce(F.sum("ends"), F.lit(0))).first()
    made = _listed(clean, keys, n) if 0 < n <= PACKED_NODES and 0 < rows <= 2 * PACKED_ROWS else None
    made = _joined(clean, keys) if made is None else made
    discard(clean)
    return made


def _listed(clean: DataFrame, keys: DataFrame, n: int) -> Graph | None:
    """The graph as lists of packed numbers; None where two keys have one hash. A key reaches the tasks as its hash and its node."""
    lists.by_value()
    spark = clean.sparkSession
    hashes, nodes, ends = lists.opened(keys.select(F.xxhash64("key"), "node", "ends").mapInArrow(lists.table, lists.TABLE).collect())
    if (hashes[1:] == hashes[:-1]).any():
        return None
    firsts, shared = lists.ranges(ends), spark.sparkContext.broadcast((hashes, nodes))
    codes = clean.select(F.xxhash64("a").alias("a"), F.xxhash64("b").alias("b")).mapInArrow(lists.coded(shared, firsts), lists.CODES)
    held = cut(codes.repartitionById(len(firsts), "range").mapInArrow(lists.listed(firsts, n), lists.LISTS), "lists")
    shared.destroy()
    sizes = {r.range: (r.held, r.most) for r in held.select("range", "held", "most").collect()}
    offsets = [0]
    for i in range(len(firsts)):
        offsets.append(offsets[-1] + sizes.get(i, (0, 0))[0])
    deg = held.select("first", "deg").mapInArrow(lists.degrees, "node long, deg long")
    named = keys.join(deg, "node", "left").select(
        "node", "key", F.substring_index("key", ":", 1).alias("kind"), F.coalesce("deg", F.lit(0).cast("long")).alias("deg")
    )
    stats = Stats(n, offsets[-1] // 2, max(most for _, most in sizes.values()))
    made = Listed(None, cut(named, "nodes"), stats, lists=held, offsets=tuple(offsets[:-1]))
    release(spark)
    return made


def _joined(clean: DataFrame, keys: DataFrame) -> Graph:
    """The graph by joins of its pairs with its nodes, for any size."""
    both = cut(normalise(clean), "pairs")
    release(both.sparkSession)
    degrees = both.groupBy(F.col("a").alias("key")).agg(F.count("*").alias("deg"))
    named = keys.join(degrees, "key", "left").select(
        "node", "key", F.substring_index("key", ":", 1).alias("kind"), F.coalesce("deg", F.lit(0).cast("long")).alias("deg")
    )
    nodes = cut(named, "nodes")
    release(both.sparkSession)
    name = nodes.select("node", "key")
    pairs = both.join(name.toDF("src", "a"), "a").join(name.toDF("dst", "b"), "b").select("src", "dst")
    edges = cut(with_pos(pairs, nodes), "edges")
    release(both.sparkSession)
    return Graph(edges, nodes, measure(nodes))


def block(edges: DataFrame, size: int = BLOCK) -> DataFrame:
    """adj(src, block, nbr, nbr_deg, deg): at most `size` neighbours a row, in list order."""
    packed = edges.groupBy("src", F.expr(f"cast((pos - 1) div {size} as int)").alias("block")).agg(
        F.sort_array(F.collect_list(F.struct("pos", "dst", "dst_deg"))).alias("held"), F.first("src_deg").alias("deg")
    )
    return packed.select("src", "block", F.col("held.dst").alias("nbr"), F.col("held.dst_deg").alias("nbr_deg"), "deg")


def unblock(adj: DataFrame, size: int = BLOCK) -> DataFrame:
    opened = adj.select("src", "block", "deg", F.posexplode(F.arrays_zip("nbr", "nbr_deg")).alias("i", "x"))
    return opened.select(
        "src", F.col("x.nbr").alias("dst"), (F.col("block") * size + F.col("i") + 1).cast("int").alias("pos"),
        F.col("deg").alias("src_deg"), F.col("x.nbr_deg").alias("dst_deg"),
    )


def bucket_of(node: Column, buckets: int) -> Column:
    return F.pmod(F.hash(node.cast("long")), F.lit(buckets))


def bucketed(adj: DataFrame, buckets: int) -> DataFrame:
    with_bucket = adj.withColumn("bucket", bucket_of(F.col("src"), buckets))
    return with_bucket.repartition(buckets, "bucket").sortWithinPartitions("bucket", "src", "block")


def pruned(adj: DataFrame, frontier: list[int], buckets: int = 64) -> DataFrame:
    """Rows of a small frontier; its buckets and ids reach the scan as filters."""
    spark = adj.sparkSession
    ids = spark.createDataFrame([(x,) for x in frontier], "src long")
    wanted = sorted({r[0] for r in ids.select(F.pmod(F.hash("src"), F.lit(buckets))).distinct().collect()})
    return adj.filter(F.col("bucket").isin(wanted) & F.col("src").isin(list(frontier)))


_built: dict[tuple[str, str, str], Graph] = {}


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """The named graph of a data folder; built once a session."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _built:
        _built[key] = build(GRAPHS[name](spark, sf_dir))
    return _built[key]


def stats(spark: SparkSession, sf_dir: str, name: str) -> Stats:
    """The named graph's statistics, which need its degrees only: no ids, places or edges are made for them."""
    held = _built.get((spark.sparkContext.applicationId, sf_dir, name))
    if held is not None:
        return held.stats
    return measure(normalise(GRAPHS[name](spark, sf_dir)).groupBy("a").agg(F.count("*").alias("deg")))


def components(g: Graph) -> DataFrame:
    """(node, comp): the least node that each node reaches; labels spread and jump until none changes."""
    pairs = g.edges.select("src", "dst")
    labels = cut(g.nodes.select("node", F.col("node").alias("comp")), "labels")
    total = None
    while True:
        told = pairs.join(labels, pairs["src"] == labels["node"]).select(F.col("dst").alias("node"), "comp")
        least = told.union(labels).groupBy("node").agg(F.min("comp").alias("comp"))
        own = labels.select(F.col("node").alias("comp"), F.col("comp").alias("further"))
        labels = cut(least.join(own, "comp").select("node", F.least("comp", "further").alias("comp")), "labels")
        now = labels.agg(F.sum(F.col("comp").cast("decimal(38,0)"))).first()[0]
        if now == total:
            return labels
        total = now


def common_neighbours(g: Graph, pairs: DataFrame) -> DataFrame:
    """(u, v, common) for stated pairs (u, v)."""
    left = pairs.join(g.edges.select(F.col("src").alias("u"), F.col("dst").alias("w")), "u")
    both = left.join(g.edges.select(F.col("src").alias("v"), F.col("dst").alias("w")), ["v", "w"])
    return both.groupBy("u", "v").agg(F.count("*").alias("common"))


def edge_diff(before: DataFrame, after: DataFrame) -> DataFrame:
    """(a, b, change): edges that came or went between two snapshots of normalised edges."""
    came = after.exceptAll(before).withColumn("change", F.lit("added"))
    return came.union(before.exceptAll(after).withColumn("change", F.lit("removed")))
