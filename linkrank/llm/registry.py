"""Queries of the corpus operators, and the SQL they are compared with."""

from __future__ import annotations

from importlib import import_module

#: Modules with QUERY (name), query (function) and, where SQL can express it, ORACLE.
MODULES = ("decontaminate", "jaccard", "language", "lines", "quality", "mixing", "pii", "repeats", "toxicity", "vectors")


def queries() -> dict:
    return {m.QUERY: m.query for m in _modules()}


def oracle_sql() -> dict:
    return {m.QUERY: m.ORACLE for m in _modules() if getattr(m, "ORACLE", None)}


def _modules():
    return [import_module(f"linkrank.llm.{name}") for name in MODULES]
