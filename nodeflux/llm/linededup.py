"""Line dedup over range-partitioned line hashes [native].

Every line key of a minimum length becomes one slim row (hash, document, position).
The rows are range-partitioned by hash and sorted by document and position, so that one
streaming pass sees the first occurrence of a key and then the lines to drop. What comes
back is a bitmap of dropped lines for each document (64 lines a word, words without a
drop left out), not text.

Defined results: a null or empty text is one empty line; lines whose key is short are
never dropped; a null doc_id counts as the least id, ids may be of any type that has an order; rows that repeat a doc_id with
another text are told apart by the text's hash and count as one document; an empty table
gives an empty result; other columns of the input play no part.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WHITE, cut, fresh_names, lower_ascii, partitions, row_id

#: A sample of about so many line rows finds the hot keys; their number is at most SAMPLE / HOT_IN_SAMPLE.
SAMPLE, HOT_IN_SAMPLE, SLICES = 200_000, 100, 64


def _text() -> Column:
    return F.coalesce(F.col("text"), F.lit(""))


def line_rows(docs: DataFrame, min_chars: int) -> DataFrame:
    """(h1, h2, id, th, pos): a row for each line whose key has min_chars code points."""
    lines = docs.select(
        F.col("doc_id").alias("id"),
        F.xxhash64(_text()).alias("th"),
        F.posexplode(F.split(_text(), "\n", -1)).alias("pos", "line"),
    )
    keyed = lines.select("id", "th", "pos", F.btrim("line", F.lit(WHITE)).alias("key")).filter(
        F.char_length("key") >= min_chars
    )
    key = lower_ascii(F.col("key"))
    return keyed.select(
        F.xxhash64(key).alias("h1"), F.xxhash64(F.lit(11), key).alias("h2"), "id", "th", "pos"
    )


def hot_keys(rows: DataFrame, n_rows: int) -> DataFrame:
    """(h1, h2, hot_docs, hot_last) of keys that hold a large share of all rows; exact counts.

    The sample only decides which keys are dealt out in slices; it changes no result.
    """
    share = min(1.0, SAMPLE / max(n_rows, 1))
    found = (
        rows.sample(share, seed=7).groupBy("h1", "h2").count()
        .filter(F.col("count") >= HOT_IN_SAMPLE).select("h1", "h2")
    )
    return (
        rows.join(F.broadcast(found), ["h1", "h2"]).select("h1", "h2", "id").distinct()
        .groupBy("h1", "h2").agg(F.count("*").alias("hot_docs"), F.max("id").alias("hot_last"))
    )


def dropped_lines(docs: DataFrame, min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    """(id, th, pos) of each line to drop: its key is in min_docs documents, and not in a larger doc_id."""
    rows = cut(line_rows(docs, min_chars), "lines")
    hot = cut(hot_keys(rows, rows.count()), "hot-lines")
    salted = rows.join(F.broadcast(hot), ["h1", "h2"], "left").withColumn(
        "slice", F.when(F.col("hot_docs").isNull(), 0).otherwise(F.pmod(F.xxhash64("id"), F.lit(SLICES)))
    )
    ranged = salted.repartitionByRange(partitions(docs), "h1", "h2", "slice")
    ranged = ranged.sortWithinPartitions("h1", "h2", "slice", F.desc("id"), "pos")
    stream = Window.partitionBy("h1", "h2", "slice").orderBy(F.desc("id"))
    ranked = ranged.withColumn("nth", F.dense_rank().over(stream)).withColumn(
        "seen", F.max("nth").over(stream.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    )
    cold = F.col("hot_docs").isNull()
    drop = F.when(cold, (F.col("seen") >= min_docs) & (F.col("nth") > 1)).otherwise(
        (F.col("hot_docs") >= min_docs) & ~F.col("id").eqNullSafe(F.col("hot_last"))
    )
    return ranked.filter(drop).select("id", "th", "pos")


def drop_bitmaps(docs: DataFrame, min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    """(id, th, n_dropped, drops): drops is a sparse bitmap, an array of (word, bits), for each document that loses lines."""
    bit = F.expr("shiftleft(1L, cast(pos % 64 as int))")
    words = (
        dropped_lines(docs, min_chars, min_docs)
        .groupBy("id", "th", F.expr("cast(pos div 64 as int)").alias("word"))
        .agg(F.bit_or(bit).alias("bits"))
    )
    return words.groupBy("id", "th").agg(
        F.sum(F.bit_count("bits")).cast("long").alias("n_dropped"),
        F.sort_array(F.collect_list(F.struct("word", "bits"))).alias("drops"),
    )


def apply_bitmaps(docs: DataFrame, bitmaps: DataFrame) -> DataFrame:
    """docs with n_lines, n_dropped and kept_text; every row of docs stays, whatever it loses."""
    row, text_hash, count, drops, dense_words = fresh_names(docs, "row", "text_hash", "count", "drops", "dense_words")
    keyed = docs.withColumns({row: row_id(F.col("doc_id")), text_hash: F.xxhash64(_text())})
    marks = bitmaps.select(row_id(F.col("id")).alias(row), F.col("th").alias(text_hash), F.col("n_dropped").alias(count), F.col("drops").alias(drops))
    lines = F.split(_text(), "\n", -1)
    words = F.map_from_entries(F.col(drops))
    dense = F.transform(
        F.sequence(F.lit(0), F.element_at(F.col(drops), -1)["word"]),
        lambda w: F.coalesce(F.element_at(words, w), F.lit(0).cast("long")),
    )
    kept = F.filter(
        lines,
        lambda line, i: F.coalesce(
            F.get(F.col(dense_words), F.floor(i / 64).cast("int")).bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("long"), (i % 64).cast("int"))),
            F.lit(0).cast("long"),
        ) == 0,
    )
    return (
        keyed.join(marks, [row, text_hash], "left")
        .withColumn(dense_words, F.when(F.col(drops).isNotNull(), dense))
        .withColumns({
            "n_lines": F.size(lines).cast("long"),
            "n_dropped": F.coalesce(F.col(count), F.lit(0)).cast("long"),
            "kept_text": F.when(F.col(count).isNull(), _text()).otherwise(F.array_join(kept, "\n")),
        })
        .drop(row, text_hash, count, drops, dense_words)
    )


def dedup_lines(docs: DataFrame, min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    return apply_bitmaps(docs, drop_bitmaps(docs, min_chars, min_docs))


def op9_line_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return dedup_lines(docs).select(
        "doc_id", "n_lines", "n_dropped", F.sha2(F.col("kept_text"), 256).alias("kept_sha256")
    )


OP9_SQL = r"""
WITH lines AS (
  SELECT doc_id, unnest(ls) AS line, generate_subscripts(ls, 1) AS pos
  FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents)
), keyed AS (
  SELECT *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                      'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM lines
), common AS (
  SELECT key, max(doc_id) AS last FROM keyed WHERE length(key) >= 20
  GROUP BY key HAVING count(DISTINCT doc_id) >= 3
), marked AS (
  SELECT k.doc_id, k.pos, k.line, c.key IS NOT NULL AND k.doc_id <> c.last AS gone
  FROM keyed k LEFT JOIN common c ON k.key = c.key
)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""
