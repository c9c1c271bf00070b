"""Queries of this subpackage and the SQL that checks them."""

from __future__ import annotations

from importlib import import_module

_MODULES = {
    "op1_pivot_neardup": ("pivot_neardup", "op1_query"),
    "op2_token_counts": ("token_counts", "op2_query"),
    "op3_suffix_dedup": ("suffix_dedup", "op3_query"),
    "op4_url_rules": ("url_rules", "op4_query"),
    "op5_ngram_join": ("ngram_join", "op5_query"),
    "op6_quality_gam": ("quality_gam", "op6_query"),
    "op7_byte_gru": ("byte_gru", "op7_query"),
    "op8_matroska": ("matroska", "op8_query"),
    "op9_packing": ("packing", "op9_query"),
    "op10_mixing": ("mixing", "op10_query"),
}


def _lazy(module: str, function: str):
    return lambda spark, sf_dir: getattr(import_module(f".{module}", __package__), function)(spark, sf_dir)


def queries() -> dict:
    return {name: _lazy(*where) for name, where in _MODULES.items()}


def oracle_sql() -> dict[str, str]:
    """SQL exists for the URL rules; the others are tested against brute force, round trips or held-out accuracy."""
    from .url_rules import ORACLE_SQL

    return {"op4_url_rules": ORACLE_SQL}
