"""Chat formatting by multi-party perspective rotation [native].

For every participant of a conversation the dialogue is rendered once with that speaker as
the assistant and all others as named users; the mask holds the (start, length) spans, in
code points, of what the assistant says. A conversation is rendered in blocks of
consecutive turns, so that one very long conversation never meets in one task.

The blocks are parts of one whole: in order of block, the `rendered` of a perspective follow each
other without a gap, and `dialogues` gives the place of each part in the whole (`offset`) and the
mask in the whole's code points. Every turn, also a narrator's, stands in the whole once. A block
that is to be read by itself gets the narrators' turns of all earlier blocks at its head by
`with_scene`; that repeats text, so it is not part of the whole.

Defined results: a null text is empty, a null role is the speaker "unknown", a null turn
comes first (block -1); turns with equal numbers are ordered by role and text and repeated
rows stay; null conv_ids form one conversation; a conversation of narrators alone gives no
row; an empty table gives none; other columns of the input play no part.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Turns in a block; a longer conversation gives several rows for each perspective.
BLOCK_TURNS = 64
#: Roles that set the scene: shown in every perspective, never an assistant.
NARRATORS = ("system",)
END = "<|end|>\n"


def _escaped(c: Column) -> Column:
    """Text that looks like one of our marks must not become one."""
    return F.replace(c, F.lit("<|"), F.lit("< |"))


def _name(c: Column) -> Column:
    """A speaker's name inside a mark: it cannot close the mark or begin a line."""
    return F.translate(F.replace(_escaped(c), F.lit("|>"), F.lit("| >")), "\r\n", "  ")


def messages(conversations: DataFrame, block_turns: int = BLOCK_TURNS) -> DataFrame:
    speaker = F.coalesce(F.trim("role"), F.lit("unknown"))
    return conversations.select(
        "conv_id",
        F.coalesce(F.floor(F.col("turn") / block_turns), F.lit(-1)).cast("long").alias("block"),
        F.col("turn").alias("t"),
        _name(speaker).alias("speaker"),
        _escaped(F.coalesce(F.col("text"), F.lit(""))).alias("said"),
    )


def rotate(
    conversations: DataFrame,
    block_turns: int = BLOCK_TURNS,
    narrators: Sequence[str] = NARRATORS,
) -> DataFrame:
    """(conv_id, block, perspective, n_turns, rendered, mask, n_target_chars)."""
    rows = messages(conversations, block_turns)
    is_narrator = lambda c: c.isin(list(narrators)) if narrators else F.lit(False)
    people = rows.filter(~is_narrator(F.col("speaker"))).select(
        F.col("conv_id").alias("__conv"), F.col("speaker").alias("perspective")
    ).distinct()
    blocks = rows.groupBy("conv_id", "block").agg(
        F.sort_array(F.collect_list(F.struct("t", "speaker", "said"))).alias("turns")
    )
    seen = blocks.join(people, F.col("conv_id").eqNullSafe(F.col("__conv")))
    me = F.col("perspective")

    def head(m: Column) -> Column:
        return (
            F.when(m["speaker"] == me, "<|assistant|>\n")
            .when(is_narrator(m["speaker"]), F.concat(F.lit("<|"), m["speaker"], F.lit("|>\n")))
            .otherwise(F.concat(F.lit("<|user:"), m["speaker"], F.lit("|>\n")))
        )

    parts = F.transform(
        F.col("turns"),
        lambda m: F.struct(
            head(m).alias("head"), F.concat(m["said"], F.lit(END)).alias("body"), (m["speaker"] == me).alias("mine")
        ),
    )
    empty = F.array().cast("array<struct<start:bigint,length:bigint>>")
    mask = F.aggregate(
        F.col("parts"),
        F.struct(F.lit(0).cast("long").alias("at"), empty.alias("spans")),
        lambda acc, p: F.struct(
            (acc["at"] + F.char_length(p["head"]) + F.char_length(p["body"])).alias("at"),
            F.when(
                p["mine"],
                F.array_append(
                    acc["spans"],
                    F.struct(
                        (acc["at"] + F.char_length(p["head"])).alias("start"),
                        F.char_length(p["body"]).cast("long").alias("length"),
                    ),
                ),
            ).otherwise(acc["spans"]).alias("spans"),
        ),
        lambda acc: acc["spans"],
    )
    return seen.withColumn("parts", parts).select(
        "conv_id",
        "block",
        "perspective",
        F.size("turns").cast("long").alias("n_turns"),
        F.array_join(F.transform("parts", lambda p: F.concat(p["head"], p["body"])), "").alias("rendered"),
        mask.alias("mask"),
    ).withColumn(
        "n_target_chars", F.aggregate("mask", F.lit(0).cast("long"), lambda a, s: a + s["length"])
    )


def dialogues(conversations: DataFrame, block_turns: int = BLOCK_TURNS, narrators: Sequence[str] = NARRATORS) -> DataFrame:
    """rotate's rows with `offset`, the code points of the whole dialogue before the block, and `mask` counted from the whole's start.

    Only lengths are added up over a dialogue; its texts never meet in one task.
    """
    rows = rotate(conversations, block_turns, narrators)
    length = F.char_length("rendered").cast("long")
    before = Window.partitionBy("__conv", "__who").orderBy("__block").rowsBetween(Window.unboundedPreceding, -1)
    places = rows.select(
        F.col("conv_id").alias("__conv"), F.col("perspective").alias("__who"), F.col("block").alias("__block"), length.alias("__n")
    ).withColumn("offset", F.coalesce(F.sum("__n").over(before), F.lit(0)).cast("long"))
    same = F.col("conv_id").eqNullSafe(F.col("__conv")) & (F.col("perspective") == F.col("__who")) & (F.col("block") == F.col("__block"))
    shifted = F.transform("mask", lambda s: F.struct((s["start"] + F.col("offset")).alias("start"), s["length"].alias("length")))
    return rows.join(places, same).withColumn("mask", shifted).select(*rows.columns, "offset")


def with_scene(rows: DataFrame, conversations: DataFrame, block_turns: int = BLOCK_TURNS, narrators: Sequence[str] = NARRATORS) -> DataFrame:
    """rotate's rows with the narrators' turns of all earlier blocks at the head of `rendered`, `mask` shifted by them (`scene_length`)."""
    told = messages(conversations, block_turns).filter(F.col("speaker").isin(list(narrators)))
    text = F.concat(F.lit("<|"), F.col("speaker"), F.lit("|>\n"), F.col("said"), F.lit(END))
    scenes = told.select(F.col("conv_id").alias("__conv"), F.struct("block", "t", "speaker", "said", text.alias("text")).alias("turn"))
    keys = rows.select("conv_id", "block").distinct()
    heads = keys.join(scenes, F.col("conv_id").eqNullSafe(F.col("__conv")) & (F.col("turn.block") < F.col("block"))).groupBy("conv_id", "block").agg(
        F.array_join(F.transform(F.sort_array(F.collect_list("turn")), lambda t: t["text"]), "").alias("scene")
    ).select(F.col("conv_id").alias("__conv"), F.col("block").alias("__block"), "scene")
    headed = rows.join(heads, F.col("conv_id").eqNullSafe(F.col("__conv")) & (F.col("block") == F.col("__block")), "left")
    headed = headed.withColumn("scene", F.coalesce("scene", F.lit(""))).withColumn("scene_length", F.char_length("scene").cast("long"))
    shifted = F.transform("mask", lambda s: F.struct((s["start"] + F.col("scene_length")).alias("start"), s["length"].alias("length")))
    return headed.withColumn("rendered", F.concat("scene", "rendered")).withColumn("mask", shifted).select(*rows.columns, "scene_length")


def op4_chat_dialogues(spark, sf_dir: str) -> DataFrame:
    """The parts of whole dialogues: op4_chat_formatting's rows with their offsets and the mask of the whole."""
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    return dialogues(turns).select(
        "conv_id", "block", "perspective", "n_turns", "n_target_chars", "offset",
        F.array_join(F.transform("mask", lambda s: F.concat_ws("+", s["start"].cast("string"), s["length"].cast("string"))), ",").alias("mask_spans"),
        F.sha2("rendered", 256).alias("rendered_sha256"),
    )


def op4_chat_formatting(spark, sf_dir: str) -> DataFrame:
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    return rotate(turns).select(
        "conv_id", "block", "perspective", "n_turns", "n_target_chars",
        F.array_join(F.transform("mask", lambda s: F.concat_ws("+", s["start"].cast("string"), s["length"].cast("string"))), ",").alias("mask_spans"),
        F.sha2("rendered", 256).alias("rendered_sha256"),
    )


OP4_SQL = r"""
WITH m AS (
  SELECT conv_id, coalesce(floor(turn / 64), -1)::BIGINT AS block, turn,
         translate(replace(replace(coalesce(trim(role), 'unknown'), '<|', '< |'), '|>', '| >'), chr(13) || chr(10), '  ') AS speaker,
         replace(coalesce(text, ''), '<|', '< |') || '<|end|>' || chr(10) AS body
  FROM conversations
), p AS (
  SELECT DISTINCT conv_id, speaker AS perspective FROM m WHERE speaker <> 'system'
), x AS (
  SELECT m.*, perspective, speaker = perspective AS mine,
         CASE WHEN speaker = perspective THEN '<|assistant|>' WHEN speaker = 'system' THEN '<|system|>'
              ELSE '<|user:' || speaker || '|>' END || chr(10) AS head
  FROM m JOIN p ON m.conv_id IS NOT DISTINCT FROM p.conv_id
), y AS (
  SELECT *, sum(length(head) + length(body)) OVER (PARTITION BY conv_id, block, perspective
           ORDER BY turn NULLS FIRST, speaker, body ROWS UNBOUNDED PRECEDING) - length(body) AS start
  FROM x
)
SELECT conv_id, block, perspective, count(*) AS n_turns,
       coalesce(sum(length(body)) FILTER (WHERE mine), 0)::BIGINT AS n_target_chars,
       coalesce(string_agg(start::BIGINT || '+' || length(body), ',' ORDER BY start) FILTER (WHERE mine), '') AS mask_spans,
       sha256(string_agg(head || body, '' ORDER BY start)) AS rendered_sha256
FROM y GROUP BY conv_id, block, perspective
"""
