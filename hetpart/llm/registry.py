"""Queries of the corpus operators and the SQL that checks those that SQL can express."""

from __future__ import annotations

import importlib

from .oracles import SQL

#: query name -> (module, function); modules load when a query is made.
_WHERE = {
    "op1_tool_calls": "tool_calls",
    "op2_quality_cnn": "quality_cnn",
    "op3_pii": "pii",
    "op4_bpe": "bpe",
    "op5_toxicity": "toxicity",
    "op6_suffix_dedup": "suffix_dedup",
    "op7_langid": "langid",
    "op8_decontaminate": "decontaminate",
    "op9_near_dup": "near_dup",
    "op10_line_rules": "line_rules",
}



def _query(module: str, name: str):
    return lambda spark, sf_dir: getattr(importlib.import_module(f"{__package__}.{module}"), name)(spark, sf_dir)


QUERIES = {name: _query(module, name) for name, module in _WHERE.items()}
