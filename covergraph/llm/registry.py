"""Queries and SQL of the training-data operators."""

from __future__ import annotations

from . import embedding_dedup, language_model, license_scan, mixing, packing, quality_classifier, quality_rules, simhash, suffix_dedup, url_filter

QUERIES = {
    "op1_best_fit_packing": packing.op1_best_fit_packing,
    "op2_mix_sources": mixing.op2_mix_sources,
    "op3_license_scan": license_scan.op3_license_scan,
    "op4_suffix_dedup": suffix_dedup.op4_suffix_dedup,
    "op5_language_model": language_model.op5_language_model,
    "op6_simhash": simhash.op6_simhash,
    "op7_quality_rules": quality_rules.op7_quality_rules,
    "op8_quality_classifier": quality_classifier.op8_quality_classifier,
    "op9_url_filter": url_filter.op9_url_filter,
    "op10_embedding_dedup": embedding_dedup.op10_embedding_dedup,
}
ORACLES = {
    "op7_quality_rules": quality_rules.ORACLE,
    "op9_url_filter": url_filter.ORACLE,
    "op10_embedding_dedup": embedding_dedup.ORACLE,
}
