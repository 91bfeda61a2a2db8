"""Queries and SQL of the operators in this package, for the driver's entry module."""

from __future__ import annotations

import importlib

MODULES = {
    "op3_merkle_fixity_audit": "fixity",
    "op8_log_frequency_bloom_lm": "lmscore",
    "op1_random_forest_secrets": "secrets",
    "op9_signature_rule_licenses": "licenses",
    "op6_noisy_channel_toxicity": "toxicity",
    "op10_word_backoff_language": "language",
    "op4_term_at_a_time_topk": "topk",
    "op7_bin_completion_packing": "packing",
    "op2_wu_manber_decontamination": "decontaminate",
    "op5_ngram_jaccard_join": "jaccard",
}


def queries() -> dict:
    return {name: getattr(importlib.import_module(f"{__package__}.{module}"), name) for name, module in MODULES.items()}


def oracle_sql() -> dict[str, str]:
    found = {name: getattr(importlib.import_module(f"{__package__}.{module}"), "SQL", None) for name, module in MODULES.items()}
    return {name: sql for name, sql in found.items() if sql}
