"""Queries and oracle SQL of the training-data operators."""

from __future__ import annotations

from . import op1_langid, op2_suffix_dedup, op3_mix, op4_html, op5_quality, op6_lm, op7_simhash, op8_classifier, op9_decontaminate, op10_secrets

QUERIES = {
    "op1_language_id": op1_langid.op1_language_id,
    "op2_suffix_dedup": op2_suffix_dedup.op2_suffix_dedup,
    "op3_mix_sources": op3_mix.op3_mix_sources,
    "op4_html_extract": op4_html.op4_html_extract,
    "op5_quality_rules": op5_quality.op5_quality_rules,
    "op6_lm_score": op6_lm.op6_lm_score,
    "op7_simhash_dedup": op7_simhash.op7_simhash_dedup,
    "op8_quality_classifier": op8_classifier.op8_quality_classifier,
    "op9_decontaminate": op9_decontaminate.op9_decontaminate,
    "op10_secret_scan": op10_secrets.op10_secret_scan,
}

ORACLES = {
    "op3_mix_sources": op3_mix.oracle(),
    "op5_quality_rules": op5_quality.oracle(),
    "op6_lm_score": op6_lm.oracle(),
    "op9_decontaminate": op9_decontaminate.oracle(),
}
