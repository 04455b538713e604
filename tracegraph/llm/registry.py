"""Queries of the corpus operators and the SQL they are held against."""

from __future__ import annotations

import importlib

#: module -> query
MODULES = {
    "quality_mcd": "op1_quality_mcd",
    "shard_propagation": "op2_balanced_label_propagation",
    "tool_calls": "op3_tool_call_linking",
    "license_rules": "op6_license_rules",
    "wrapper_induction": "op5_wrapper_induction",
    "pii_disclosure": "op7_pii_disclosure",
    "deleted_interpolation": "op4_deleted_interpolation",
    "decontamination": "op9_decontamination",
    "token_groups": "op8_token_group_join",
    "packing_nnls": "op10_nnls_packing",
}


def queries() -> dict:
    return {name: getattr(importlib.import_module(f"{__package__}.{m}"), name) for m, name in MODULES.items()}


def oracle_sql() -> dict[str, str]:
    found = {}
    for m, name in MODULES.items():
        sql = getattr(importlib.import_module(f"{__package__}.{m}"), "ORACLE_SQL", None)
        if sql:
            found[name] = sql
    return found
