"""Registry of the training-data queries and the SQL that checks them."""

from __future__ import annotations

from bandspark.llm import bpe, exactdup, langid, linededup, lm, mixing, ngramjoin, pii, quality, secretscan


def queries() -> dict:
    return {"op1_language_id": langid.query, "op2_ngram_join": ngramjoin.query, "op3_personal_data": pii.query, "op4_lm_scores": lm.query, "op5_line_dedup": linededup.query, "op6_bpe_round_trip": bpe.query, "op7_secret_scan": secretscan.query, "op8_exact_dedup": exactdup.query, "op9_mix_sources": mixing.query, "op10_quality_rules": quality.query}


def oracle_sql() -> dict:
    return {"op2_ngram_join": ngramjoin.ORACLE_SQL, "op5_line_dedup": linededup.ORACLE_SQL, "op8_exact_dedup": exactdup.ORACLE_SQL, "op9_mix_sources": mixing.ORACLE_SQL}
