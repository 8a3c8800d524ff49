"""Queries of this subpackage and, where SQL can say the same, their SQL."""

from __future__ import annotations

from importlib import import_module

_OPERATORS = {
    "op1_simhash": "simhash",
    "op2_exact_dedup": "exact_dedup",
    "op3_line_dedup": "line_dedup",
    "op4_substring_dedup": "substring_dedup",
    "op5_pii": "pii",
    "op6_url_filter": "url_filter",
    "op7_langid": "langid",
    "op8_bpe": "bpe",
    "op9_toxicity": "toxicity",
    "op10_decontaminate": "decontaminate",
}
_MODULES = {name: import_module(f"flowrings.llm.{module}") for name, module in _OPERATORS.items()}
QUERIES = {name: getattr(module, name) for name, module in _MODULES.items()}
ORACLES = {name: module.ORACLE for name, module in _MODULES.items() if hasattr(module, "ORACLE")}
