"""Queries of the training-data operators and the SQL that checks them."""

from __future__ import annotations

from boundpath.llm import ctw, decontaminate, mixing, neardup, quality, sharding, tokencount, toxicity, urlgraph, warc

_MODULES = [decontaminate, ctw, tokencount, sharding, quality, toxicity, neardup, urlgraph, mixing, warc]


def queries() -> dict:
    return {name: f for m in _MODULES for name, f in m.QUERIES.items()}


def oracle_sql() -> dict:
    return {name: sql for m in _MODULES for name, sql in getattr(m, "ORACLES", {}).items()}
