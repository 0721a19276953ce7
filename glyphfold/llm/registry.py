"""Queries and SQL of the training-data operators."""

from __future__ import annotations

from importlib import import_module

#: Query name and the module that holds it.
MODULES = {
    "op1_suffix_array_dedup": "suffix_dedup",
    "op2_quality_rules": "quality_rules",
    "op3_url_filter": "url_filter",
    "op4_cotrained_quality": "cotraining",
    "op5_benchmark_decontamination": "decontaminate",
    "op6_personal_data": "pii_crf",
    "op7_interpolated_lm": "interpolated_lm",
    "op8_bin_slack_packing": "bin_packing",
    "op9_simhash_near_dedup": "simhash_dedup",
    "op10_hilbert_sharding": "hilbert_shards",
}


def queries() -> dict:
    found = {name: import_module(f"glyphfold.llm.{module}").query for name, module in MODULES.items()}
    return found | {"pipeline": import_module("corpus_pipeline").run}


def oracle_sql() -> dict[str, str]:
    out = {}
    for name, module in MODULES.items():
        sql = getattr(import_module(f"glyphfold.llm.{module}"), "ORACLE_SQL", None)
        if sql:
            out[name] = sql
    return out
