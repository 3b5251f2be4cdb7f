"""The queries of this subpackage and the SQL that checks them."""

from __future__ import annotations

from redgraph.llm import chat_repair, decontamination, exact_dedup, lm_scoring, mixing, sharding, simhash, substring_dedup, toxicity, url_filters

QUERIES = {
    "op1_decontamination": decontamination.op1_decontamination,
    "op2_substring_dedup": substring_dedup.op2_substring_dedup,
    "op3_sharding": sharding.op3_sharding,
    "op4_exact_dedup": exact_dedup.op4_exact_dedup,
    "op5_toxicity": toxicity.op5_toxicity,
    "op6_url_filters": url_filters.op6_url_filters,
    "op7_simhash": simhash.op7_simhash,
    "op8_lm_scoring": lm_scoring.op8_lm_scoring,
    "op9_chat_repair": chat_repair.op9_chat_repair,
    "op10_mixing": mixing.op10_mixing,
}

ORACLES = {
    "op1_decontamination": decontamination.SQL,
    "op3_sharding": sharding.SQL,
    "op4_exact_dedup": exact_dedup.SQL,
    "op6_url_filters": url_filters.SQL,
    "op8_lm_scoring": lm_scoring.SQL,
    "op10_mixing": mixing.SQL,
}
