"""Quality rules as a short-circuit cascade [native].

Measures are array expressions over one text each, so nothing is shuffled. The verdict is
a CASE whose branches are the rules, so a text that one rejects is not held against the
rest. A bounded sample gives each rule's cost, as work counted on the rows (characters that
it scans) and not as seconds, and its rejections among the rows that all rules before it
leave; the next branch is always the one that rejects most per cost. So the order is the same in
each run over one table. All orders give the same verdict; the order only decides how soon a
bad text is done with.

`apply_rules` returns the measures of every row, so only what rules count beyond them is
short-circuited. The measures stand behind a generator of one row, which no filter is pushed
through: else a filter on the verdict would compute them anew wherever they are used.

Defined results: a null or empty text has no words and fails the base rule; every row gives
one row, repeated ids too; an empty table gives an empty result and the rules' given order;
ties of rejection per cost go by the given order; other columns of the input play no part.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WHITE, fresh_names

#: Rows of the sample that orders the rules, taken from the first partitions.
SAMPLE_ROWS = 2000


@dataclass(frozen=True)
class Rule:
    """A text fails if `fails` is true; it may use the measures' columns and `text`. `work` counts what that costs a row."""

    name: str
    fails: Column
    work: Column | None = None


def _count(chars: str) -> Column:
    return F.size(F.regexp_extract_all(F.col("text"), F.lit(chars), F.lit(0)))


def default_rules() -> list[Rule]:
    n, scan = F.col("n_words"), F.char_length("text")
    return [
        Rule("symbols", 10 * F.col("n_symbols") > n, F.lit(2)),
        Rule("repeated_lines", (F.col("n_dup_lines") >= 3) & (2 * F.col("n_dup_lines") > F.col("n_text_lines")), F.lit(3)),
        Rule("word_length", (F.col("word_chars") > 14 * n) | (F.col("word_chars") < 2 * n), F.lit(3)),
        Rule("capitals", 2 * _count("[A-Z]") > F.col("word_chars"), scan),
        Rule("exclamations", 2 * _count("!") > n, scan),
        Rule("digits", 2 * _count("[0-9]") > F.col("word_chars"), scan),
    ]


def repeated_words(words: Column, hashes: Column, width: int = 5) -> Column:
    """Words in windows that occur twice or more; hashes: one for each window start."""
    marked = F.array_sort(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    same = lambda s, e, j: F.coalesce(F.get(s, j)["h"] == e["h"], F.lit(False))
    twice = F.filter(F.col("__marked"), lambda e, j: same(F.col("__marked"), e, j - 1) | same(F.col("__marked"), e, j + 1))
    starts = F.array_sort(F.transform(twice, lambda e: e["i"]))
    covered = F.aggregate(
        starts,
        F.struct(F.lit(0).cast("long").alias("sum"), F.lit(-width).alias("last")),
        lambda acc, i: F.struct(
            (acc["sum"] + F.least(F.lit(width), i - acc["last"])).alias("sum"), i.alias("last")
        ),
        lambda acc: acc["sum"],
    )
    return marked, covered


def measure(docs: DataFrame) -> DataFrame:
    """docs with n_words, word_chars, n_symbols, n_dup_lines, n_text_lines, n_repeat_words; these replace columns of docs of these names."""
    docs = docs.drop("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_text_lines", "n_repeat_words")
    text = F.coalesce(F.col("text"), F.lit(""))
    words = F.filter(F.split(text, r"[\x20\x09-\x0D]+", -1), lambda w: w != "")
    lines = F.filter(F.split(text, "\n", -1), lambda x: F.btrim(x, F.lit(WHITE)) != "")
    width = 5
    window = F.transform(
        F.sequence(F.lit(0), F.size("__words") - width),
        lambda i: F.xxhash64(*[F.get(F.col("__words"), i + k) for k in range(width)]),
    )
    marked, covered = repeated_words(F.col("__words"), F.col("__hashes"), width)
    return (
        docs.withColumns({"__words": words, "__lines": lines})
        .withColumn("__hashes", F.when(F.size("__words") >= width, window))
        # only a text in which a window occurs twice is sorted
        .withColumn("__marked", F.when(F.size(F.array_distinct("__hashes")) < F.size("__hashes"), marked))
        .select(*[F.col(c) for c in docs.columns], F.inline(F.array(F.struct(
            F.size("__words").cast("long").alias("n_words"),
            F.char_length(F.array_join("__words", "")).cast("long").alias("word_chars"),
            F.size(F.regexp_extract_all(text, F.lit("[#*$%&|<>]"), F.lit(0))).cast("long").alias("n_symbols"),
            F.size("__lines").cast("long").alias("n_text_lines"),
            (F.size("__lines") - F.size(F.array_distinct("__lines"))).cast("long").alias("n_dup_lines"),
            F.when(F.col("__marked").isNull(), 0).otherwise(covered).cast("long").alias("n_repeat_words"),
        ))))
    )


def base_failed() -> Column:
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def order_rules(docs: DataFrame, rules: Sequence[Rule], sample_rows: int = SAMPLE_ROWS) -> list[Rule]:
    """Rules by rejection per work among what the rules before them leave of a sample, the most first."""
    flag = lambda c: F.coalesce(c, F.lit(False))
    work = [F.coalesce(r.work if r.work is not None else F.char_length("text"), F.lit(0)).cast("double") for r in rules]
    seen = measure(docs).select(flag(base_failed()).alias("out"), F.array(*[flag(r.fails) for r in rules]).alias("fails"), F.array(*work).alias("work"))
    # a limit at the very end reads partitions one after another until it has its rows, and shuffles nothing
    rows = [r for r in seen.limit(sample_rows).collect() if not r.out]
    left, order = list(range(len(rules))), []
    while left:
        cost = {k: sum(r.work[k] for r in rows) for k in left}
        best = max(left, key=lambda k: (sum(r.fails[k] for r in rows) / max(cost[k], 1.0), -k))
        order.append(rules[best])
        left.remove(best)
        rows = [r for r in rows if not r.fails[best]]
    return order


def cascade(rules: Sequence[Rule]) -> Column:
    verdict = F.when(base_failed(), False)
    for rule in rules:
        verdict = verdict.when(rule.fails, False)
    return verdict.otherwise(True)


def apply_rules(docs: DataFrame, rules: Sequence[Rule] | None = None) -> DataFrame:
    """docs with the measures, base_failed and kept."""
    ordered = order_rules(docs, rules or default_rules())
    return measure(docs).withColumns({"base_failed": base_failed(), "kept": cascade(ordered)})


def keep_documents(docs: DataFrame, rules: Sequence[Rule] | None = None) -> DataFrame:
    """The rows of docs that pass, with their columns as they are, also those that are called like a measure."""
    (whole,) = fresh_names(docs, "whole_row")
    marked = apply_rules(docs.select("text", F.struct(*docs.columns).alias(whole)), rules)
    return marked.filter("kept").select(*[F.col(whole)[c].alias(c) for c in docs.columns])


def op6_quality_rules(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return apply_rules(docs).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"
    )


OP6_SQL = r"""
WITH d AS (
  SELECT doc_id, coalesce(text, '') AS text,
         regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words,
         list_filter(string_split(coalesce(text, ''), chr(10)), lambda l: regexp_matches(l, '[^\x20\x09-\x0D]')) AS lines
  FROM documents
), w AS (
  SELECT doc_id, unnest(range(1, len(words) - 3)) AS i, words FROM d WHERE len(words) >= 5
), g AS (
  SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, array_to_string(words[i:i+4], ' ')) AS c FROM w
), r AS (
  SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + 5)) AS p FROM g WHERE c >= 2) GROUP BY doc_id
), m AS (
  SELECT d.doc_id, text, len(words) AS n_words, len(array_to_string(words, '')) AS word_chars,
         len(regexp_extract_all(text, '[#*$%&|<>]')) AS n_symbols,
         len(lines) - len(list_distinct(lines)) AS n_dup_lines, len(lines) AS n_text_lines,
         coalesce(r.n, 0) AS n_repeat_words
  FROM d LEFT JOIN r ON d.doc_id = r.doc_id
), b AS (
  SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM m
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT (base_failed OR 10 * n_symbols > n_words OR (n_dup_lines >= 3 AND 2 * n_dup_lines > n_text_lines)
            OR word_chars > 14 * n_words OR word_chars < 2 * n_words
            OR 2 * len(regexp_extract_all(text, '[A-Z]')) > word_chars
            OR 2 * len(regexp_extract_all(text, '!')) > n_words
            OR 2 * len(regexp_extract_all(text, '[0-9]')) > word_chars) AS kept
FROM b
"""
