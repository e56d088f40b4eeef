"""The queries of this subpackage and the SQL that they are compared with."""

from __future__ import annotations

import importlib

#: query -> module that has it; a query's function is named after its operator.
QUERIES = {
    "op1_near_duplicates": "graphwatch.llm.neardup:op1_query",
    "op2_license_scan": "graphwatch.llm.licenses:op2_query",
    "op3_decontaminate": "graphwatch.llm.decontaminate:op3_query",
    "op4_token_files": "graphwatch.llm.tokenfiles:op4_query",
    "op5_url_filter": "graphwatch.llm.urlfilter:op5_query",
    "op6_mix_sources": "graphwatch.llm.mixing:op6_query",
    "op7_page_text": "graphwatch.llm.pagetext:op7_query",
    "op8_line_dedup": "graphwatch.llm.linededup:op8_query",
    "op9_lm_score": "graphwatch.llm.lmscore:op9_query",
    "op10_quality_rules": "graphwatch.llm.quality:op10_query",
    "pipeline": "corpus_pipeline:run",
}


def queries() -> dict:
    out = {}
    for name, where in QUERIES.items():
        module, function = where.split(":")
        out[name] = getattr(importlib.import_module(module), function)
    return out


def oracle_sql() -> dict[str, str]:
    from graphwatch.llm import oracles

    return dict(oracles.SQL)
