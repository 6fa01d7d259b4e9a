"""The thin queries of this subpackage, by the names that `__spark_entry__.py` registers."""

from __future__ import annotations

from runstore.llm import decontaminate, interleave, language_id, license_scan, lm_score, near_dup, piece_codec, quality, token_store, vector_dup

QUERIES = {
    "op1_vector_dup": vector_dup.query,
    "op2_token_store": token_store.query,
    "op3_interleave": interleave.query,
    "op4_near_dup": near_dup.query,
    "op5_language_id": language_id.query,
    "op6_lm_score_whole": lm_score.query_whole,
    "op7_decontaminate": decontaminate.query,
    "op8_piece_codec": piece_codec.query,
    "op9_license_scan": license_scan.query,
    "op10_quality": quality.query,
}
ORACLES: dict[str, str] = {"op6_lm_score_whole": lm_score.ORACLE_WHOLE}
