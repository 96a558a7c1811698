"""The registered queries of the training-data operators and their SQL, where SQL can express them."""

from __future__ import annotations

import importlib

#: query name -> module of this subpackage
_MODULES = {
    "op1_ngram_jaccard_join": "setjoin",
    "op2_byte_bpe": "bpe",
    "op3_suffix_dedup": "repeats",
    "op4_toxicity": "toxicity",
    "op5_exact_topk": "vafile",
    "op6_warc_derivatives": "warc",
    "op7_language_id": "langid",
    "op8_decontamination": "decontam",
    "op9_pii_surrogates": "pii",
    "op10_html_extraction": "htmltext",
}


def queries() -> dict:
    return {name: importlib.import_module(f"elastipool.llm.{m}").query for name, m in _MODULES.items()}


def oracle_sql() -> dict[str, str]:
    out = {}
    for name, m in _MODULES.items():
        sql = getattr(importlib.import_module(f"elastipool.llm.{m}"), "ORACLE_SQL", None)
        if sql:
            out[name] = sql
    return out
