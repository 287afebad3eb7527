"""Sharding by vector bin packing over bytes, tokens and rows.

Rows with equal texts form a group. A group that holds a share of 1/UNITS of the bytes,
tokens or rows is a unit of its own; all other groups are gathered by their hash into
CELLS units. So the driver places a bounded number of vectors, whatever the input: in
decreasing order, each goes to the shard where the dot product of its vector with the
shard's residual capacity is highest, among the shards that still have its bytes free.
Only a group above a whole shard is split, into slices by doc_id.

Slots are gapless: a unit's first slot comes from the driver's sums, the rank inside it
from a window over one slice of a unit (slices are small even for a group that holds a
third of all rows).

Defined results: a null text has no bytes and counts one byte as any row does; repeated
rows each get a slot; ties in the order by doc_id are broken by size and checksum; an
empty table gives an empty result; other columns of the input play no part.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut

#: Bound on the driver's table: CELLS + 3 * UNITS units and as many slices again.
CELLS, UNITS = 8192, 2048
#: Bytes count for more than tokens and rows, as the law is about bytes.
WEIGHTS = (4.0, 1.0, 1.0)


@dataclass(frozen=True)
class Placement:
    shard: np.ndarray
    loads: np.ndarray


def place(vectors: np.ndarray, n_shards: int, weights: tuple[float, ...] = WEIGHTS) -> Placement:
    """Shard of each vector (rows: units; columns: bytes, tokens, rows)."""
    total = np.maximum(vectors.sum(axis=0), 1)
    scaled = vectors / total
    residual = np.full((n_shards, vectors.shape[1]), 1.0 / n_shards)
    w = np.asarray(weights)
    shard = np.zeros(len(vectors), dtype=np.int64)
    for i in np.lexsort((np.arange(len(vectors)), -scaled[:, 0], -scaled.max(axis=1))):
        v = scaled[i]
        score = residual @ (v * w)
        fits = residual[:, 0] >= v[0]
        best = int(np.argmax(np.where(fits, score, -np.inf))) if fits.any() else int(np.argmax(residual[:, 0]))
        shard[i] = best
        residual[best] -= v
    return Placement(shard, (1.0 / n_shards - residual) * total)


def measured(docs: DataFrame, tokens: Column | None = None) -> DataFrame:
    """(doc_id, size, tokens, crc, th, th2); tokens: pieces between spaces unless another measure is given."""
    text = F.coalesce(F.col("text"), F.lit(""))
    spaces = F.octet_length(text) - F.octet_length(F.replace(text, F.lit(" "), F.lit(""))) + 1
    return docs.select(
        "doc_id",
        (F.octet_length(text) + 1).cast("long").alias("size"),
        (tokens if tokens is not None else spaces).cast("long").alias("tokens"),
        F.crc32(text.cast("binary")).alias("crc"),
        F.xxhash64(text).alias("th"),
        F.xxhash64(F.lit(5), text).alias("th2"),
    )


def shard_documents(docs: DataFrame, n_shards: int = 8, tokens: Column | None = None) -> DataFrame:
    """(doc_id, size, text_crc32, shard, slot)."""
    spark = docs.sparkSession
    slim = cut(measured(docs, tokens), "shard-rows")
    sums = [F.sum("size").alias("bytes"), F.sum("tokens").alias("toks"), F.count("*").alias("n")]
    total = [int(x or 0) for x in slim.agg(*sums).first()]
    share = F.greatest(*[F.col(c) / F.lit(float(max(t, 1))) for c, t in zip(("bytes", "toks", "n"), total, strict=True)])
    # at most 3 * UNITS groups, as each holds 1 / UNITS of one of three sums
    groups = cut(
        slim.groupBy("th", "th2").agg(*sums).withColumn("share", share).filter(F.col("share") >= 1.0 / UNITS)
        .select("th", "th2", (F.col("share") > 1.0 / n_shards).alias("huge"), F.ceil(F.col("share") * UNITS).alias("slices")),
        "shard-groups",
    )
    own = F.col("slices").isNotNull()
    keyed = slim.join(F.broadcast(groups), ["th", "th2"], "left").select(
        "doc_id", "size", "tokens", "crc",
        F.coalesce("huge", F.lit(False)).alias("huge"),
        own.alias("own"),
        F.when(own, F.col("th")).otherwise(F.pmod("th", F.lit(CELLS))).alias("a"),
        F.when(own, F.col("th2")).otherwise(0).alias("b"),
        F.when(own, F.pmod(F.xxhash64("doc_id"), "slices")).otherwise(0).alias("slice"),
    )
    found = keyed.groupBy("huge", "own", "a", "b", "slice").agg(*sums).toPandas()
    found = found.sort_values(["own", "a", "b", "slice"], ignore_index=True)
    found["part"] = found["slice"].where(found["huge"], 0)
    unit = found.groupby(["own", "a", "b", "part"], sort=False).ngroup().to_numpy() if len(found) else np.zeros(0, int)
    vectors = np.zeros((unit.max() + 1 if len(unit) else 0, 3))
    np.add.at(vectors, unit, found[["bytes", "toks", "n"]].to_numpy(dtype=float))
    found["shard"] = place(vectors, n_shards).shard[unit] if len(unit) else []
    found["first"] = found.groupby("shard")["n"].cumsum() - found["n"] if len(found) else []
    rows = [(bool(o), int(a), int(b), int(s), int(x), int(f)) for o, a, b, s, x, f in
            found[["own", "a", "b", "slice", "shard", "first"]].itertuples(index=False)]
    placed = spark.createDataFrame(rows, "own boolean, a long, b long, slice long, shard int, first long")
    rank = Window.partitionBy("own", "a", "b", "slice").orderBy("doc_id", "size", "crc")
    return (
        keyed.withColumn("slice", F.col("slice").cast("long")).withColumn("nth", F.row_number().over(rank))
        .join(F.broadcast(placed), ["own", "a", "b", "slice"])
        .select("doc_id", "size", F.col("crc").alias("text_crc32"), "shard", (F.col("first") + F.col("nth") - 1).alias("slot"))
    )


def op7_sharding(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return shard_documents(docs, 8).select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard")
    )
