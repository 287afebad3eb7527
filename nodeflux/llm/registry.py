"""Queries of this package and their DuckDB twins."""

from __future__ import annotations

from . import chat, classifier, decontaminate, jaccard, linededup, packing, rules, sharding, substrings, warc

QUERIES = {
    "op1_quality_classifier": classifier.op1_quality_classifier,
    "op2_decontamination": decontaminate.op2_decontamination,
    "op3_best_fit_packing": packing.op3_best_fit_packing,
    "op4_chat_formatting": chat.op4_chat_formatting,
    "op4_chat_dialogues": chat.op4_chat_dialogues,
    "op5_warc": warc.op5_warc,
    "op6_quality_rules": rules.op6_quality_rules,
    "op7_sharding": sharding.op7_sharding,
    "op8_jaccard_join": jaccard.op8_jaccard_join,
    "op9_line_dedup": linededup.op9_line_dedup,
    "op10_suffix_dedup": substrings.op10_suffix_dedup,
}
ORACLES = {
    "op2_decontamination": decontaminate.OP2_SQL,
    "op4_chat_formatting": chat.OP4_SQL,
    "op5_warc": warc.OP5_SQL,
    "op6_quality_rules": rules.OP6_SQL,
    "op9_line_dedup": linededup.OP9_SQL,
}
