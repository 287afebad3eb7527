"""The corpus pipeline: quality, lines, near copies, benchmark leaks, packing.

Each stage takes (spark, docs, sf_dir) and returns what its predecessor kept, less what it
rejects, with the columns of documents; the last one returns the packed pieces.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nodeflux.llm import classifier, decontaminate, jaccard, linededup, packing
from nodeflux.llm.common import cut


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier gives label 1; learned from labels outside the held-out third.

    Null and empty texts get the prior's score; repeated rows are scored each for itself.
    """
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality").filter(~classifier.held_out())
    return classifier.keep_good(docs, classifier.fit(docs, labels))


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the lines that three documents share, but for the largest doc_id's; n_chars follows the text.

    Every row stays; a null text becomes empty, a null doc_id counts as the least one.
    """
    whole = docs.select("doc_id", "text", F.struct(*docs.columns).alias("__row"))
    done = linededup.dedup_lines(whole)
    new = {"text": F.col("kept_text"), "n_chars": F.char_length("kept_text").cast("long")}
    return done.select(*[new.get(c, F.col("__row")[c]).alias(c) for c in docs.columns])


def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of texts that share four in five of their five-word shingles: the least doc_id's.

    Rows without doc_id or words stay; rows that repeat a doc_id are judged each by its own text.
    """
    return jaccard.keep_first(docs, 5, 80)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no window of a benchmark item; null and empty texts hold none, repeated rows stay repeated."""
    items = spark.read.parquet(f"{sf_dir}/benchmark.parquet").select("item_id", "text")
    return decontaminate.remove_leaks(docs, items)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in bins; a null or empty text has its end mark, a null doc_id stays null, each row is packed for itself."""
    return packing.pack(docs.select("doc_id", "text"))


STAGES = [
    ("quality_classifier", keep_quality),
    ("line_dedup", drop_repeated_lines),
    ("ngram_jaccard_join", keep_one_of_near_copies),
    ("benchmark_decontamination", drop_leaks),
    ("best_fit_packing", pack),
]

#: Embeddings trained by gradient descent and sequential packing have no SQL form; tests hold run() against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = cut(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
