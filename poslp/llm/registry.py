"""The queries of this subpackage and the DuckDB texts that check them."""

from __future__ import annotations

from importlib import import_module

_QUERIES = {
    "op1_nn_descent": "nn_descent",
    "op2_secret_scan": "secret_scan",
    "op3_packing": "packing",
    "op4_line_dedup": "line_dedup",
    "op5_mixing": "mixing",
    "op6_suffix_dedup": "suffix_dedup",
    "op7_quality_rules": "quality_rules",
    "op8_chat_format": "chat_format",
    "op9_token_blocks": "token_blocks",
    "op10_simhash": "simhash",
}


def queries() -> dict:
    return {name: getattr(import_module(f"poslp.llm.{module}"), name) for name, module in _QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    found = {name: getattr(import_module(f"poslp.llm.{module}"), "ORACLE", None) for name, module in _QUERIES.items()}
    return {name: sql for name, sql in found.items() if sql}
