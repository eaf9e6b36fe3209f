"""Registered queries of the engine and the SQL that gives the same rows."""

from __future__ import annotations

from . import balance_queries, operator_queries, tissue_queries

MODULES = (tissue_queries, balance_queries, operator_queries)


def queries() -> dict:
    return {name: q for m in MODULES for name, q in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: s for m in MODULES for name, s in m.ORACLES.items()}
