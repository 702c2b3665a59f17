"""Queries and DuckDB oracles of this subpackage."""

from __future__ import annotations

from importlib import import_module

#: Operators in the order of their numbers.
MODULES = (
    "quality_classifier minhash_forest quality_rules exact_dedup bpe_codec license_scan html_extract token_output "
    "suffix_dedup packing"
).split()


def queries() -> dict:
    return {k: f for m in MODULES for k, f in import_module(f"walkengine.llm.{m}").QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: s for m in MODULES for k, s in import_module(f"walkengine.llm.{m}").ORACLES.items()}
