"""Whole hop series as products of packed blocks of the adjacency with packed ranges of vectors.

A row of blocks holds edges from one range of senders to one range of receivers, a row of a
state the vectors of one range. A hop reads the blocks once and shuffles ranges, not edges.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nodeflux.plans.storage import cut, discard

from .graph import Graph

#: Nodes of a range, and edges of a block about.
WIDTH, EDGES = 1 << 18, 1 << 20
#: Vectors that go through one pass; more take the plans by rows.
SLOTS = 16
#: Ranges of vectors are broadcast up to so many bytes; else the blocks are shuffled to them.
BROADCAST_BYTES = 32 << 20
#: A row is a block or a range, so readers and batches take few at once.
_FEW = {"spark.sql.execution.arrow.maxRecordsPerBatch": "4", "spark.sql.parquet.columnarReaderBatchSize": "4"}
_STATE = "part int, deg binary, value binary, x binary, cost binary"


def width(g: Graph) -> int:
    """Nodes of a range of this graph."""
    return max(1, min(WIDTH, g.stats.n))


def blocks(g: Graph) -> DataFrame:
    """(i, j, src, dst): 32-bit places inside range j of senders and range i of receivers; written once a graph."""
    if getattr(g, "_blocks", None) is None:
        wide = width(g)
        ranges = -(-g.stats.n // wide)
        salts = max(1, 2 * g.stats.m // (ranges * ranges * EDGES))
        part = lambda c: F.expr(f"cast({c} div {wide} as int)")
        rows = g.edges.select(part("dst").alias("i"), part("src").alias("j"), F.pmod("src", F.lit(salts)).cast("int").alias("salt"),
                              F.pmod("src", F.lit(wide)).cast("int").alias("src"), F.pmod("dst", F.lit(wide)).cast("int").alias("dst"))
        dealt = rows.repartition(max(ranges * ranges * salts, g.spark.sparkContext.defaultParallelism), "i", "j", "salt")
        g._blocks = cut(dealt.mapInArrow(_pack_edges, "i int, j int, src binary, dst binary"), "blocks")
    return g._blocks


def _pack_edges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held: dict[tuple[int, int], list] = {}
    sizes: dict[tuple[int, int], int] = {}

    def block(key: tuple[int, int]) -> pa.RecordBatch:
        src, dst = (np.concatenate(x).tobytes() for x in zip(*held.pop(key)))
        sizes.pop(key)
        return pa.RecordBatch.from_arrays([pa.array([key[0]], pa.int32()), pa.array([key[1]], pa.int32()), pa.array([src], pa.binary()), pa.array([dst], pa.binary())], ["i", "j", "src", "dst"])

    for batch in batches:
        i, j, src, dst = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("i", "j", "src", "dst"))
        pair = i.astype(np.int64) << 32 | j
        order = np.argsort(pair, kind="stable")
        for at in np.split(order, np.flatnonzero(np.diff(pair[order])) + 1) if len(order) else []:
            key = int(i[at[0]]), int(j[at[0]])
            held.setdefault(key, []).append((src[at], dst[at]))
            sizes[key] = sizes.get(key, 0) + len(at)
            if sizes[key] >= EDGES:
                yield block(key)
            elif sum(sizes.values()) >= 4 * EDGES:
                yield block(max(sizes, key=sizes.get))
    for key in list(held):
        yield block(key)


def _range(part: int, deg: np.ndarray, value: np.ndarray, r: np.ndarray, cost: np.ndarray, decay: float, weight: float, last: bool) -> pa.RecordBatch:
    """A row of a state once r is known: its share of the sum, what each node pays a neighbour, and the edges paid along."""
    value = value + weight * r
    x = decay * r / np.maximum(deg, 1)
    cost = cost if last else cost + ((r > 0) * deg).sum(axis=1)
    held = [pa.array([part], pa.int32()), *[pa.array([a.tobytes()], pa.binary()) for a in (deg, value, x, cost)]]
    return pa.RecordBatch.from_arrays(held, ["part", "deg", "value", "x", "cost"])


def _start(slots: int, wide: int, decay: float, weight: float, last: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        for batch in batches:
            node, deg, slot, r = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("node", "deg", "slot", "r"))
            for part in np.unique(node // wide).tolist():
                degs, rs = held.setdefault(part, (np.zeros(wide, np.int64), np.zeros((slots, wide))))
                mine = node // wide == part
                named, given = mine & (slot < 0), mine & (slot >= 0)
                degs[node[named] % wide] = deg[named]
                np.add.at(rs, (slot[given], node[given] % wide), r[given])
        for part, (degs, rs) in held.items():
            yield _range(part, degs, np.zeros_like(rs), rs, np.zeros(slots, np.int64), decay, weight, last)

    return run


def _paid(slots: int, wide: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}

        def out(i: int) -> pa.RecordBatch:
            empty = pa.array([None], pa.binary())
            return pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), empty, empty, pa.array([held.pop(i).tobytes()], pa.binary()), empty], ["part", "deg", "value", "x", "cost"])

        for batch in batches:
            for k in range(batch.num_rows):
                i = batch.column("i")[k].as_py()
                src, dst, x = (np.frombuffer(batch.column(c)[k].as_buffer(), kind) for c, kind in (("src", np.int32), ("dst", np.int32), ("x", np.float64)))
                if i not in held and len(held) >= 8:
                    yield out(next(iter(held)))
                r = held.setdefault(i, np.zeros((slots, wide)))
                for s, v in enumerate(x.reshape(slots, wide)):
                    if v.any():
                        r[s] += np.bincount(dst, weights=v[src], minlength=wide)
        for i in list(held):
            yield out(i)

    return run


def _summed(slots: int, wide: int, decay: float, weight: float, last: bool):
    """Rows of the state before (with degrees) and of what was paid (without) to rows of the state after."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        before: dict[int, tuple] = {}
        paid: dict[int, np.ndarray] = {}
        for batch in batches:
            for k in range(batch.num_rows):
                part, deg, value, x, cost = (batch.column(c)[k] for c in ("part", "deg", "value", "x", "cost"))
                part = part.as_py()
                if deg.is_valid:
                    before[part] = np.frombuffer(deg.as_py(), np.int64), np.frombuffer(value.as_py(), np.float64).reshape(slots, wide), np.frombuffer(cost.as_py(), np.int64)
                else:
                    r = paid.setdefault(part, np.zeros((slots, wide)))
                    r += np.frombuffer(x.as_buffer(), np.float64).reshape(slots, wide)
        for part, (deg, value, cost) in before.items():
            yield _range(part, deg, value, paid[part] if part in paid else np.zeros((slots, wide)), cost, decay, weight, last)

    return run


def series(g: Graph, start: DataFrame, slots: int, decay: float, weights: list[float]) -> DataFrame:
    """State rows after all hops, for start(slot, node, r) with slots 0 .. slots - 1: value is the sum of weights[l] * r_l,
    cost the edges that all hops paid along. One job a hop; the driver sees ranges only where they are broadcast."""
    spark, own = g.spark, {k: g.spark.conf.get(k) for k in _FEW}
    cloudpickle.register_pickle_by_value(sys.modules[__name__])
    held = blocks(g)
    wide = width(g)
    ranges, last = max(1, -(-g.stats.n // wide)), len(weights) - 1
    none = F.lit(0).cast("long")
    rows = g.nodes.select("node", F.col("deg").cast("long").alias("deg"), F.lit(-1).cast("long").alias("slot"), F.lit(0.0).alias("r")).unionByName(
        start.select("node", none.alias("deg"), F.col("slot").cast("long").alias("slot"), "r"))
    state = cut(rows.repartition(ranges, F.expr(f"node div {wide}")).mapInArrow(_start(slots, wide, decay, weights[0], not last), _STATE), "ranges")
    small = ranges * wide * 8 * slots <= BROADCAST_BYTES
    for k, v in _FEW.items():
        spark.conf.set(k, v)
    try:
        for hop in range(1, last + 1):
            x = state.select(F.col("part").alias("j"), "x")
            paid = held.join(F.broadcast(x) if small else x.hint("shuffle_hash"), "j").select("i", "src", "dst", "x").mapInArrow(_paid(slots, wide), _STATE)
            both = state.select("part", "deg", "value", F.lit(None).cast("binary").alias("x"), "cost").unionByName(paid)
            after = cut(both.repartition(ranges, "part").mapInArrow(_summed(slots, wide, decay, weights[hop], hop == last), _STATE), "ranges")
            discard(state)
            state = after
    finally:
        for k, v in own.items():
            spark.conf.set(k, v)
    return state


def values(g: Graph, state: DataFrame, slots: int) -> DataFrame:
    """(slot, node, value) of all values above 0."""
    wide = width(g)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, held in zip(batch.column("part").to_pylist(), batch.column("value")):
                for s, v in enumerate(np.frombuffer(held.as_buffer(), np.float64).reshape(slots, wide)):
                    at = np.flatnonzero(v)
                    for a in range(0, len(at), 1 << 16):
                        k = at[a : a + (1 << 16)]
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(k), s, np.int32)), pa.array(k + part * wide), pa.array(v[k])], ["slot", "node", "value"])

    return state.mapInArrow(run, "slot int, node long, value double")


def sums(g: Graph, state: DataFrame, slots: int) -> DataFrame:
    """(slot, by_deg, cost): each slot's sum of value over degree, and the edges it paid along."""
    wide = width(g)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for deg, value, cost in zip(*[batch.column(c) for c in ("deg", "value", "cost")]):
                v = np.frombuffer(value.as_buffer(), np.float64).reshape(slots, wide)
                by_deg = (v / np.maximum(np.frombuffer(deg.as_buffer(), np.int64), 1)).sum(axis=1)
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(slots, dtype=np.int32)), pa.array(by_deg), pa.array(np.frombuffer(cost.as_buffer(), np.int64))], ["slot", "by_deg", "cost"])

    return state.mapInArrow(run, "slot int, by_deg double, cost long").groupBy("slot").agg(F.sum("by_deg").alias("by_deg"), F.sum("cost").alias("cost"))
