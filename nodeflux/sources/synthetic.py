"""Graphs of known shape as a data source: spark.read.format("shapes").option("shape", "star").option("size", 100)."""

from __future__ import annotations

import sys
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class NodeRange(InputPartition):
    """Nodes first <= i < last, whose edges one task makes."""

    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class ShapeReader(DataSourceReader):
    def __init__(self, shape: str, size: int, seed: int, parts: int):
        if shape not in ("star", "complete", "cycle", "attached"):
            raise ValueError(f"no shape {shape}")
        self.shape, self.size, self.seed, self.parts = shape, size, seed, parts

    def partitions(self) -> list[NodeRange]:
        step = max(1, -(-self.size // self.parts))
        return [NodeRange(a, min(a + step, self.size)) for a in range(0, max(self.size, 1), step)]

    def read(self, partition: NodeRange) -> Iterator[tuple[int, int]]:
        for i in range(partition.first, partition.last):
            yield from edges_of(self.shape, self.size, self.seed, i)


def edges_of(shape: str, size: int, seed: int, i: int) -> Iterator[tuple[int, int]]:
    """The edges that node i of a shape of `size` nodes brings."""
    import hashlib

    if shape == "complete":
        yield from ((i, j) for j in range(i + 1, size))
    elif shape == "cycle":
        if size > 2:
            yield i, (i + 1) % size
    elif i > 0:
        u = (int(hashlib.md5(f"{seed}|{i}".encode()).hexdigest()[:12], 16) + 0.5) / float(1 << 48)
        yield i, 0 if shape == "star" else int(i * u * u)


def over(keys: DataFrame, shape: str, seed: int = 0) -> DataFrame:
    """(a, b): the shape whose nodes are a table's distinct keys(key), numbered in their order; nulls go."""
    from pyspark import cloudpickle

    from nodeflux.operators.graph import dense_ids

    cloudpickle.register_pickle_by_value(sys.modules[__name__])
    nodes = dense_ids(keys.filter("key is not null"))
    size = nodes.count()

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for some in _chunks(x for i in batch.column("node").to_pylist() for x in edges_of(shape, size, seed, i)):
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*some)], ["a", "b"])

    return nodes.select("node").mapInArrow(make, "a long, b long")


def _chunks(rows: Iterator[tuple[int, int]], size: int = 100_000) -> Iterator[list[tuple[int, int]]]:
    from itertools import islice

    while some := list(islice(rows, size)):
        yield some


class Shapes(DataSource):
    """Rows (a, b), each edge once. "attached" joins each node to an earlier one, early ones more often: a heavy-tailed tree.

    Options: shape, size (nodes), seed, parts (tasks). No edges come of a size below two.
    """

    @classmethod
    def name(cls) -> str:
        return "shapes"

    def schema(self) -> str:
        return "a long, b long"

    def reader(self, schema) -> ShapeReader:
        o = self.options
        return ShapeReader(o.get("shape", "star"), int(o.get("size", "0")), int(o.get("seed", "0")), int(o.get("parts", "8")))


def register(spark: SparkSession) -> None:
    from pyspark import cloudpickle

    cloudpickle.register_pickle_by_value(sys.modules[__name__])
    spark.dataSource.register(Shapes)
