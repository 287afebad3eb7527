"""Best-fit packing into sequences of several permitted lengths.

Documents longer than the longest permitted length are cut into pieces. Pieces of equal
length are interchangeable, so packing works on the histogram of lengths: best-fit in order
of decreasing length places runs of pieces into runs of bins, and its plan depends on the
longest length and not on the number of documents. It is the plan that sequential best-fit
would make. Each way to open bins (least cost a token, least cost, least cost a token that pieces
of this length would fill) is planned to the end; after that every bin is downsized to the least permitted length that holds its
contents, and the plan of least total cost is taken.

Pieces find their place by rank within their length: offsets by (length, slice) are summed
on the driver (a bounded table), ranks inside a slice come from a window.

Defined results: a null text has no tokens but its end mark; repeated rows are packed each
for itself; ties are broken by doc_id and piece; an empty table gives none; other columns
of the input play no part.
"""

from __future__ import annotations

from collections import defaultdict, deque
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, ship

#: Permitted sequence lengths, in tokens; the default tokens are UTF-8 bytes and an end mark.
LENGTHS = (2048, 4096, 8192, 16384)
#: A sequence costs its length and this much.
OVERHEAD = 128
SLICES = 4096


@dataclass
class Plan:
    #: pieces of length[i] with ranks from rank[i] on go to bins from bin[i] on, at offset[i]
    length: np.ndarray
    rank: np.ndarray
    bin: np.ndarray
    offset: np.ndarray
    #: bins from first_bin[i] on have capacity[i]
    first_bin: np.ndarray
    capacity: np.ndarray
    n_bins: int
    cost: float


def best_fit(counts: dict[int, int], lengths: Sequence[int], costs: dict[int, float], opened: Callable[[int], int]) -> Plan:
    """Best-fit over a histogram of piece lengths; opened(length) is the size of a new bin."""
    classes: dict[int, deque] = defaultdict(deque)  # residual -> runs (first bin, bins, capacity)
    filled = 0  # bit r is set if a bin has residual r
    runs: list[tuple[int, int, int, int]] = []
    n_bins = 0
    for length in sorted(counts, reverse=True):
        left, rank = counts[length], 0
        while left:
            above = filled >> length
            if above:
                r = length + (above & -above).bit_length() - 1
                first, bins, capacity = classes[r].popleft()
                if not classes[r]:
                    filled &= ~(1 << r)
            else:
                capacity = r = opened(length)
                each = r // length
                first, bins = n_bins, max(1, left // each)
                n_bins += bins
            each = r // length
            used = min(bins, left // each)
            if not used:
                used, each = 1, left
            for k in range(each):
                runs.append((length, rank, first, capacity - r + k * length))
                rank += used
            left -= used * each
            for some, at, residual in ((used, first, r - each * length), (bins - used, first + used, r)):
                if some:
                    classes[residual].append((at, some, capacity))
                    filled |= 1 << residual
    ends = sorted((first, capacity - r, bins) for r, held in classes.items() for first, bins, capacity in held)
    fits = np.array(sorted(lengths))
    capacity = fits[np.searchsorted(fits, [content for _, content, _ in ends])] if ends else np.zeros(0, np.int64)
    total = float(sum(costs[int(c)] * bins for c, (_, _, bins) in zip(capacity, ends, strict=True)))
    table = np.array(sorted(runs), dtype=np.int64).reshape(-1, 4)
    return Plan(*table.T, np.array([first for first, _, _ in ends], dtype=np.int64), capacity, n_bins, total)


def plan_bins(counts: dict[int, int], lengths: Sequence[int] = LENGTHS, costs: dict[int, float] | None = None) -> Plan:
    """The plan of least cost among the ways to open bins."""
    costs = costs or {c: c + OVERHEAD for c in lengths}
    ways = (lambda c, n: costs[c] / c, lambda c, n: costs[c], lambda c, n: costs[c] / (c // n * n))
    plans = [
        best_fit(counts, lengths, costs, lambda n, way=way: min((c for c in lengths if c >= n), key=lambda c: (way(c, n), -c)))
        for way in ways
    ]
    return min(plans, key=lambda p: p.cost)


def pieces(docs: DataFrame, longest: int, tokens: Column | None = None) -> DataFrame:
    """(doc_id, piece, n_pieces, length)."""
    n = (tokens if tokens is not None else F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long")
    cutoff = docs.select("doc_id", n.alias("tokens")).filter("tokens > 0").withColumn("n_pieces", F.ceil(F.col("tokens") / longest).cast("int"))
    return cutoff.select(
        "doc_id", "n_pieces", "tokens", F.explode(F.sequence(F.lit(0), F.col("n_pieces") - 1)).alias("piece")
    ).select("doc_id", "piece", "n_pieces", F.least(F.lit(longest), F.col("tokens") - F.col("piece").cast("long") * longest).cast("int").alias("length"))


def placer(shared):
    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plan = shared.value
        keys = plan.length * (1 << 44) + plan.rank
        for batch in batches:
            rank = batch.column("rank").to_numpy(zero_copy_only=False)
            key = batch.column("length").to_numpy(zero_copy_only=False).astype(np.int64) * (1 << 44) + rank
            run = np.searchsorted(keys, key, side="right") - 1
            bins = plan.bin[run] + rank - plan.rank[run]
            size = plan.capacity[np.searchsorted(plan.first_bin, bins, side="right") - 1]
            keep = [c for c in batch.schema.names if c != "rank"]
            yield pa.RecordBatch.from_arrays(
                [batch.column(c) for c in keep] + [pa.array(bins), pa.array(size.astype(np.int32)), pa.array(plan.offset[run].astype(np.int32))],
                [*keep, "bin_id", "bin_capacity", "bin_offset"],
            )

    return place


def pack(docs: DataFrame, lengths: Sequence[int] = LENGTHS, costs: dict[int, float] | None = None, tokens: Column | None = None) -> DataFrame:
    """(doc_id, piece, n_pieces, length, bin_id, bin_capacity, bin_offset)."""
    ship("nodeflux.llm.packing")
    spark = docs.sparkSession
    items = cut(pieces(docs, max(lengths), tokens), "pack-pieces")
    counts = {r["length"]: r["count"] for r in items.groupBy("length").count().collect()}
    total = max(1, sum(counts.values()))
    sliced = spark.createDataFrame(
        [(n, -(-c * SLICES // total)) for n, c in sorted(counts.items())], "length int, slices int"
    )
    keyed = items.join(F.broadcast(sliced), "length").withColumn("slice", F.pmod(F.xxhash64("doc_id", "piece"), "slices")).drop("slices")
    sums, first, at = keyed.groupBy("length", "slice").count().collect(), [], defaultdict(int)
    for n, s, c in sorted(sums):
        first.append((n, s, at[n]))
        at[n] += c
    offsets = spark.createDataFrame(first, "length int, slice long, first long")
    within = F.row_number().over(Window.partitionBy("length", "slice").orderBy("doc_id", "piece"))
    ranked = keyed.withColumn("nth", within).join(F.broadcast(offsets), ["length", "slice"])
    kind = docs.schema["doc_id"].dataType.simpleString()
    shared = spark.sparkContext.broadcast(plan_bins(counts, lengths, costs))
    return ranked.select(
        "doc_id", "piece", "n_pieces", "length", (F.col("first") + F.col("nth") - 1).alias("rank")
    ).mapInArrow(placer(shared), f"doc_id {kind}, piece int, n_pieces int, length int, bin_id long, bin_capacity int, bin_offset int")


def op3_best_fit_packing(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return pack(docs)
