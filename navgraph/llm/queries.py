"""The registered queries of this subpackage and their SQL."""

from __future__ import annotations

from importlib import import_module

#: Query name and the module that has it.
WHERE = {
    "op1_toxicity": "toxicity",
    "op4_exact_topk": "topk",
    "op2_ngram_jaccard_join": "jaccard",
    "op8_substring_dedup": "substrings",
    "op5_lm_scoring": "ngram_lm",
    "op3_language_id": "langid",
    "op6_warc_transactions": "warc",
    "op7_secret_scans": "secrets",
    "op9_benchmark_decontamination": "decontaminate",
    "op10_mixing_sources": "mixing",
}


def queries() -> dict:
    return {name: getattr(import_module(f"navgraph.llm.{module}"), name) for name, module in WHERE.items()}


def oracle_sql() -> dict:
    found = {name: getattr(import_module(f"navgraph.llm.{module}"), "SQL", None) for name, module in WHERE.items()}
    return {name: sql for name, sql in found.items() if sql}
