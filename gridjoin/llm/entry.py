"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from importlib import import_module

#: module, query, whether it has SQL
OPERATORS = [
    ("ann", "op1_ann", False),
    ("decontaminate", "op2_decontaminate", True),
    ("pieces", "op3_sentencepiece", False),
    ("warc", "op4_warc", True),
    ("html_extract", "op5_html_extract", False),
    ("pii", "op6_pii", True),
    ("language_id", "op7_language_id", False),
    ("lm_score", "op8_lm_score", False),
    ("line_dedup", "op9_line_dedup", True),
    ("ngram_join", "op10_ngram_join", True),
]


def queries() -> dict:
    return {q: getattr(import_module(f"gridjoin.llm.{m}"), q) for m, q, _ in OPERATORS} | {"pipeline": import_module("corpus_pipeline").run}


def oracle_sql() -> dict[str, str]:
    found = {q: import_module(f"gridjoin.llm.{m}").oracle() for m, q, sql in OPERATORS if sql}
    pipeline = import_module("corpus_pipeline").ORACLE_SQL
    return found | ({"pipeline": pipeline} if pipeline else {})
