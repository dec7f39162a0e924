"""Registered queries of this subpackage and their DuckDB SQL."""

from __future__ import annotations

from importlib import import_module

from ..functions.deploy import ship

#: query name -> module with query(spark, sf_dir) and, where SQL can express it, ORACLE_SQL
MODULES = {
    "op1_secret_scan": "secrets",
    "op2_license_scan": "licenses",
    "op3_minhash_dedup": "near_dup",
    "op4_decontaminate": "decontaminate",
    "op5_feistel_shards": "sharding",
    "op6_hpy_scores": "pitman_yor",
    "op7_html_extract": "html_text",
    "op8_decision_list": "quality_rules",
    "op9_pow2_packing": "packing",
    "op10_mil_quality": "mil_quality",
}
#: The columns of an operator that SQL can express, where it can't express all: query name -> module with base_query and BASE_SQL
BASES = {"base_language_scores": "pitman_yor", "base_quality_counts": "quality_rules"}


def _call(module: str, function: str):
    query = getattr(import_module(f"{__package__}.{module}"), function)
    return lambda spark, sf_dir: query(ship(spark), sf_dir)


def queries():
    return {name: _call(module, "query") for name, module in MODULES.items()} | {name: _call(module, "base_query") for name, module in BASES.items()}


def oracle_sql():
    found = {name: getattr(import_module(f"{__package__}.{module}"), "ORACLE_SQL", None) for name, module in MODULES.items()}
    found |= {name: import_module(f"{__package__}.{module}").BASE_SQL for name, module in BASES.items()}
    return {name: sql for name, sql in found.items() if sql}
