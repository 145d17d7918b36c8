"""The training-data queries and their SQL counterparts."""

from __future__ import annotations

from cutfold.llm import exact_dedup, language_id, line_dedup, mixing, pieces, pii, simhash_dedup, sketches, substring_dedup, toxicity

QUERIES = {
    "op1_mix_sources": mixing.op1_mix_sources,
    "op2_sentence_pieces": pieces.op2_sentence_pieces,
    "op3_substring_dedup": substring_dedup.op3_substring_dedup,
    "op4_language_id": language_id.op4_language_id,
    "op5_line_dedup": line_dedup.op5_line_dedup,
    "op6_exact_dedup": exact_dedup.op6_exact_dedup,
    "op7_personal_data": pii.op7_personal_data,
    "op8_simhash_dedup": simhash_dedup.op8_simhash_dedup,
    "op9_fingerprints": sketches.op9_fingerprints,
    "op10_toxicity": toxicity.op10_toxicity,
}
SQL = {
    "op3_substring_dedup": substring_dedup.SQL,
    "op5_line_dedup": line_dedup.SQL,
    "op6_exact_dedup": exact_dedup.SQL,
}
