"""Registry of the training-data queries and of their SQL twins."""

from __future__ import annotations

from . import chat_snapshots, decontaminate, language_mixture, media_avi, ngram_join, quality_crf, source_mix, substring_rlz, token_orc, url_rules

QUERIES = {
    "op1_quality_crf": quality_crf.op1_quality_crf,
    "op2_substring_rlz": substring_rlz.op2_substring_rlz,
    "op3_source_mix": source_mix.op3_source_mix,
    "op4_token_orc": token_orc.op4_token_orc,
    "op5_chat_snapshots": chat_snapshots.op5_chat_snapshots,
    "op6_ngram_join": ngram_join.op6_ngram_join,
    "op7_decontaminate": decontaminate.op7_decontaminate,
    "op8_language_mixture": language_mixture.op8_language_mixture,
    "op9_url_rules": url_rules.op9_url_rules,
    "op10_media_avi": media_avi.op10_media_avi,
}

ORACLES = {
    "op2_substring_rlz": substring_rlz.ORACLE,
    "op3_source_mix": source_mix.ORACLE,
    "op5_chat_snapshots": chat_snapshots.ORACLE,
    "op6_ngram_join": ngram_join.ORACLE,
    "op7_decontaminate": decontaminate.ORACLE,
    "op9_url_rules": url_rules.ORACLE,
}
