"""The queries of the training-data operators and, where SQL can express them, their oracles."""

from __future__ import annotations

import importlib

MODULES = {
    "op1_pii": "pii",
    "op2_decontamination": "decontamination",
    "op3_simhash": "simhash",
    "op4_toxicity": "toxicity",
    "op5_token_counts": "token_counts",
    "op6_quality_rules": "quality_rules",
    "op7_substring_dedup": "substring_dedup",
    "op8_packing": "packing",
    "op9_quality_classifier": "quality_classifier",
    "op10_url_filter": "url_filter",
}


def queries() -> dict:
    return {name: getattr(importlib.import_module(f"{__package__}.{module}"), name) for name, module in MODULES.items()}


def oracle_sql() -> dict[str, str]:
    out = {}
    for name, module in MODULES.items():
        sql = getattr(importlib.import_module(f"{__package__}.{module}"), "ORACLE_SQL", None)
        if sql:
            out[name] = sql
    return out
