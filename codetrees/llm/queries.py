"""The subpackage's queries and their SQL, which __spark_entry__.py adds when the subpackage is there."""

from __future__ import annotations

from codetrees.llm import chat_format, decontaminate, exact_dedup, html_extract, langid, ngram_join, packing, quality, sharding, suffix_dedup

QUERIES = {
    "op1_ngram_join": ngram_join.op1_ngram_join,
    "op2_quality": quality.op2_quality,
    "op3_exact_dedup": exact_dedup.op3_exact_dedup,
    "op4_extendible_shards": sharding.op4_extendible_shards,
    "op5_best_fit_packing": packing.op5_best_fit_packing,
    "op6_language_id": langid.op6_language_id,
    "op7_decontaminate": decontaminate.op7_decontaminate,
    "op8_suffix_dedup": suffix_dedup.op8_suffix_dedup,
    "op9_html_extract": html_extract.op9_html_extract,
    "op10_chat_format": chat_format.op10_chat_format,
}

ORACLES = {
    "op1_ngram_join": ngram_join.OP1_SQL,
    "op3_exact_dedup": exact_dedup.OP3_SQL,
    "op4_extendible_shards": sharding.op4_sql(),
    "op7_decontaminate": decontaminate.OP7_SQL,
    "op10_chat_format": chat_format.op10_sql(),
}
