"""Connected components of an edge table, without collecting any of it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, discard


def components(edges: DataFrame) -> DataFrame:
    """(id, comp): comp is the least id that links (a, b) reach; ids without links are absent.

    Each round takes the least label among the neighbours (partial sums first, so a hub
    costs one row a task) and then jumps to the label's own label; a chain of length n is
    done in about log n rounds.
    """
    both = edges.filter("a <> b").select("a", "b")
    both = cut(both.union(both.select("b", "a")).distinct(), "cc-edges")
    labels = cut(both.groupBy(F.col("a").alias("id")).agg(F.least(F.first("a"), F.min("b")).alias("comp")), "cc-labels")
    total = lambda t: t.agg(F.sum(F.col("comp").cast("decimal(38,0)"))).first()[0]
    before = total(labels)
    while before is not None:
        told = both.join(labels, both["a"] == labels["id"]).select(F.col("b").alias("id"), "comp")
        least = told.union(labels).groupBy("id").agg(F.min("comp").alias("comp"))
        own = labels.select(F.col("id").alias("comp"), F.col("comp").alias("further"))
        jumped = cut(
            least.join(own, "comp", "left").select("id", F.least("comp", F.coalesce("further", "comp")).alias("comp")),
            "cc-labels",
        )
        discard(labels)
        labels, after = jumped, total(jumped)
        if after == before:
            break
        before = after
    return labels
