"""Quality classifier: supervised subword embeddings, averaged per document.

Words, word pairs and character n-grams are hashed into a table of learned vectors; a text
is the average of its features' vectors, and a softmax over two outputs scores it. Training
is stochastic gradient descent in numpy on the driver, on a sample whose number of rows is a
parameter and does not grow with the input; tasks turn its whole texts into features. For scoring, both layers fold into one number for each
bucket (the average is linear), so a text costs one lookup a feature.

Defined results: empty and null texts have no features and get the prior's score; labels
other than 0 and 1, null ids and labels without a document are not learned from; without
labelled rows every score is 0.5; repeated rows each get a row; other columns play no part.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textkit as tk
from .common import fresh_names, ship

IDENTITY = np.arange(256, dtype=np.uint8)
SCORE = "__score"
SAME_WORD = 0x5A3D_19C6_77E4_02BF


@dataclass(frozen=True)
class Settings:
    #: log2 of the number of vectors
    bits: int = 18
    size: int = 16
    grams: tuple[int, ...] = (3, 4)
    epochs: int = 10
    rate: float = 2.0
    #: labelled documents of each class in the training sample, the first by a hash of doc_id
    per_class: int = 1000
    seed: int = 1


def features(buf: np.ndarray, bounds: np.ndarray, s: Settings) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For each kind of feature: buckets in the order of the texts, and n + 1 bounds."""
    drop = tk.U(64 - s.bits)
    w = tk.words(buf, bounds, tk.NOT_WHITE, IDENTITY)
    yield (w.hashes >> drop).astype(np.int32), w.first
    pairs = tk.windows(w.hashes, 2)
    # a word that follows itself is one feature, whatever the word
    pairs[w.hashes[1:] == w.hashes[:-1]] = tk.U(SAME_WORD)
    inside = np.ones(len(pairs), dtype=bool)
    last = w.first[1:-1]
    inside[last[(last > 0) & (last <= len(pairs))] - 1] = False
    count = np.concatenate(([0], np.cumsum(inside)))
    yield (pairs[inside] >> drop).astype(np.int32), count[np.minimum(w.first, len(pairs))]
    # characters start at bytes that do not continue one
    chars = np.flatnonzero((buf & 0xC0) != 0x80)
    first = np.searchsorted(chars, bounds)
    sums = np.zeros(len(buf) + 1, dtype=tk.U)
    np.cumsum(tk.BYTE_HASH[buf] * tk.powers(tk.BASE, len(buf)), out=sums[1:])
    edge = np.append(chars, len(buf))
    back = tk.powers(tk.BASE_INVERSE, len(buf))[chars] if len(chars) else np.zeros(0, tk.U)
    at = sums[edge]
    ends = np.repeat(first[1:], np.diff(first))
    for n in s.grams:
        if len(chars) < n:
            yield np.zeros(0, np.int32), np.zeros(len(bounds), np.int64)
            continue
        m = len(chars) - n + 1
        h = tk.mix((at[n : n + m] - at[:m]) * back[:m], n)
        inside = np.arange(n, n + m) <= ends[:m]
        count = np.concatenate(([0], np.cumsum(inside)))
        yield (h[inside] >> drop).astype(np.int32), count[np.minimum(first, m)]


def bags(texts: list[str | None], s: Settings) -> list[tuple[np.ndarray, np.ndarray]]:
    """(buckets, weights that sum to 1) of each text."""
    buf, bounds = tk.raw(pa.array(texts, pa.large_string()))
    out = []
    for a, b in tk.runs(bounds):
        kinds = list(features(buf[bounds[a] : bounds[b]], bounds[a : b + 1] - bounds[a], s))
        for i in range(b - a):
            ids, n = np.unique(np.concatenate([x[c[i] : c[i + 1]] for x, c in kinds]), return_counts=True)
            out.append((ids, (n / max(n.sum(), 1)).astype(np.float32)))
    return out


@dataclass
class Model:
    """vectors and outputs as learned; weight[b] is what bucket b adds to the logit of label 1."""

    vectors: np.ndarray
    outputs: np.ndarray
    bias: np.ndarray
    settings: Settings

    def weight(self) -> np.ndarray:
        return (self.vectors @ (self.outputs[1] - self.outputs[0])).astype(np.float32)

    def shift(self) -> float:
        return float(self.bias[1] - self.bias[0])


def train(texts: list[str | None], labels: list[int], s: Settings = Settings()) -> Model:
    return train_bags(bags(texts, s), labels, s)


def train_bags(data: list[tuple[np.ndarray, np.ndarray]], labels: list[int], s: Settings = Settings()) -> Model:
    """One step of gradient descent a document and epoch; data are the documents' bags."""
    rng = np.random.default_rng(s.seed)
    vectors = rng.uniform(-1 / s.size, 1 / s.size, (1 << s.bits, s.size)).astype(np.float32)
    outputs = np.zeros((2, s.size), dtype=np.float32)
    outputs[1] = rng.uniform(-1 / s.size, 1 / s.size, s.size)
    bias = np.zeros(2, dtype=np.float32)
    steps, done = max(1, s.epochs * len(data)), 0
    for _ in range(s.epochs):
        for i in rng.permutation(len(data)):
            ids, weights = data[i]
            rate = s.rate * (1 - done / steps)
            done += 1
            if not len(ids):
                continue
            hidden = weights @ vectors[ids]
            z = outputs @ hidden + bias
            p = np.exp(z - z.max())
            p /= p.sum()
            p[labels[i]] -= 1
            back = outputs.T @ p
            outputs -= rate * np.outer(p, hidden)
            bias -= rate * 0.1 * p
            # the average spreads a step over many features, so it is scaled up again
            vectors[ids] -= (rate * np.sqrt(len(ids))) * weights[:, None] * back[None, :]
    return Model(vectors, outputs, bias, s)


def bag_reader(s: Settings):
    """mapInArrow: (doc_id, y, th, text) to the bag of each whole text."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, text in enumerate(batch.column("text").to_pylist()):
                ids, weights = bags([text], s)[0]
                keys = [batch.column(c).slice(i, 1) for c in ("doc_id", "y", "th")]
                yield pa.RecordBatch.from_arrays([*keys, pa.array([ids], pa.list_(pa.int32())), pa.array([weights], pa.list_(pa.float32()))], ["doc_id", "y", "th", "ids", "weights"])

    return read


def sample_of(docs: DataFrame, labels: DataFrame, column: str, s: Settings) -> tuple[list[tuple[np.ndarray, np.ndarray]], list[int], float]:
    """Bags and labels of the training sample, and what the prior's log odds lack of those of all labelled rows.

    Tasks make the bags of whole texts; a bag has at most 2 ** bits entries, however long its text.
    """
    usable = labels.filter(F.col("doc_id").isNotNull() & F.col(column).isin(0, 1)).select("doc_id", F.col(column).cast("int").alias("y"))
    counts = {r.y: r["count"] for r in usable.groupBy("y").count().collect()}
    taken = None
    for y in (0, 1):
        part = usable.filter(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(s.per_class)
        taken = part if taken is None else taken.union(part)
    kind = docs.schema["doc_id"].dataType.simpleString()
    found = docs.select("doc_id", "text").filter("text is not null").join(F.broadcast(taken), "doc_id").select("doc_id", "y", F.xxhash64("text").alias("th"), "text")
    rows = found.mapInArrow(bag_reader(s), f"doc_id {kind}, y int, th long, ids array<int>, weights array<float>").toArrow()
    rows = rows.sort_by([("doc_id", "ascending"), ("y", "ascending"), ("th", "ascending")]).combine_chunks()
    odds = float(np.log(max(counts.get(1, 0), 1) / max(counts.get(0, 0), 1)))
    y = rows.column("y").to_pylist()
    data = [(i.values.to_numpy(), w.values.to_numpy()) for i, w in zip(rows.column("ids"), rows.column("weights"), strict=True)]
    seen = [sum(x == k for x in y) for k in (0, 1)]
    return data, y, odds - float(np.log(max(seen[1], 1) / max(seen[0], 1)))


def scorer(shared, name: str):
    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weight, shift, s = shared.value
        for batch in batches:
            buf, bounds = tk.raw(batch.column("text"))
            out = np.zeros(len(bounds) - 1)
            for a, b in tk.runs(bounds):
                total, n = np.zeros(b - a), np.zeros(b - a)
                for ids, cuts in features(buf[bounds[a] : bounds[b]], bounds[a : b + 1] - bounds[a], s):
                    sums = np.concatenate(([0.0], np.cumsum(weight[ids], dtype=np.float64)))
                    total += sums[cuts[1:]] - sums[cuts[:-1]]
                    n += np.diff(cuts)
                out[a:b] = 1 / (1 + np.exp(-np.clip(total / np.maximum(n, 1) + shift, -500, 500)))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out)], [*batch.schema.names, name])

    return score


def fit(docs: DataFrame, labels: DataFrame, column: str = "quality", s: Settings = Settings()) -> Model:
    ship("nodeflux.llm.textkit", "nodeflux.llm.classifier")
    data, y, odds = sample_of(docs, labels, column, s)
    model = train_bags(data, y, s)
    if data:
        model.bias[1] += odds
    else:
        model.outputs[:] = 0
    return model


def with_score(docs: DataFrame, model: Model, name: str = SCORE) -> DataFrame:
    """docs and a column `name`; nothing is shuffled."""
    ship("nodeflux.llm.textkit", "nodeflux.llm.classifier")
    shared = docs.sparkSession.sparkContext.broadcast((model.weight(), model.shift(), model.settings))
    return docs.mapInArrow(scorer(shared, name), T.StructType([*docs.schema.fields, T.StructField(name, T.DoubleType())]))


def keep_good(docs: DataFrame, model: Model, least: float = 0.5) -> DataFrame:
    """The rows of docs that score `least` or more, with their columns as they are; null and empty texts get the prior's score."""
    (name,) = fresh_names(docs, "score")
    return with_score(docs, model, name).filter(F.col(name) >= least).drop(name)


def held_out(doc_id="doc_id"):
    return F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(3)) == 1


def op1_quality_classifier(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality").filter(~held_out())
    scored = with_score(docs, fit(docs, labels))
    return scored.select("doc_id", held_out().alias("held_out"), F.col(SCORE).alias("score"), (F.col(SCORE) >= 0.5).cast("int").alias("predicted"))
