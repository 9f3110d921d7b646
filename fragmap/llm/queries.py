"""Queries of this subpackage and, where SQL can express them, their DuckDB twins."""

from __future__ import annotations

from fragmap.llm import decontaminate, licenses, line_dedup, lm_score, pieces, sharding, simhash, token_counts, toxicity, winnow

QUERIES = {
    "op1_line_dedup": line_dedup.op1_line_dedup,
    "op2_pieces": pieces.op2_pieces,
    "op3_token_counts": token_counts.op3_token_counts,
    "op4_lm_score": lm_score.op4_lm_score,
    "op5_toxicity": toxicity.op5_toxicity,
    "op6_sharding": sharding.op6_sharding,
    "op7_decontamination": decontaminate.op7_decontamination,
    "op8_simhash": simhash.op8_simhash,
    "op9_document_fingerprints": winnow.op9_document_fingerprints,
    "op10_license_scan": licenses.op10_license_scan,
}

ORACLE_SQL = {
    "op1_line_dedup": line_dedup.OP1_SQL,
}
