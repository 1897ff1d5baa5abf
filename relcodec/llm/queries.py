"""Registered queries of the ten operators, and DuckDB SQL for those it can express."""

from __future__ import annotations

from relcodec.llm import decontamination, language_id, lm_scoring, near_dup, packing, pii, quality_classifier, quality_rules, toxicity, warc_revisit

QUERIES = {
    "op1_site_quality": quality_classifier.op1_site_quality,
    "op2_mixture_language_id": language_id.op2_mixture_language_id,
    "op3_elias_fano_lm": lm_scoring.op3_elias_fano_lm,
    "op4_segment_toxicity": toxicity.op4_segment_toxicity,
    "op5_dart_minhash": near_dup.op5_dart_minhash,
    "op6_quality_rules": quality_rules.op6_quality_rules,
    "op7_cost_balanced_packing": packing.op7_cost_balanced_packing,
    "op8_revisit_resolution": warc_revisit.op8_revisit_resolution,
    "op9_surrogates": pii.op9_surrogates,
    "op10_template_decontamination": decontamination.op10_template_decontamination,
}

ORACLES: dict[str, str] = {
    "op6_quality_rules": quality_rules.ORACLE,
    "op8_revisit_resolution": warc_revisit.ORACLE,
    "op10_template_decontamination": decontamination.ORACLE,
}
