"""Queries of this subpackage and the SQL of those that SQL can express."""

from __future__ import annotations

from narrative_engine.llm import (
    decontamination,
    html_extraction,
    jaccard_join,
    language_id,
    line_dedup,
    lm_scoring,
    packing,
    quality_rules,
    token_store,
    toxicity,
)

QUERIES = {
    "op1_line_dedup": line_dedup.op1_line_dedup,
    "op2_html_extraction": html_extraction.op2_html_extraction,
    "op3_token_store": token_store.op3_token_store,
    "op4_toxicity": toxicity.op4_toxicity,
    "op5_decontamination": decontamination.op5_decontamination,
    "op6_jaccard_join": jaccard_join.op6_jaccard_join,
    "op7_language_id": language_id.op7_language_id,
    "op8_quality_rules": quality_rules.op8_quality_rules,
    "op9_best_fit_packing": packing.op9_best_fit_packing,
    "op10_lm_scoring": lm_scoring.op10_lm_scoring,
}
ORACLES = {
    "op5_decontamination": decontamination.ORACLE,
    "op6_jaccard_join": jaccard_join.ORACLE,
    "op8_quality_rules": quality_rules.ORACLE,
}
