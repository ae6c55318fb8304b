"""The library's queries and the SQL that checks them, by workload."""

from __future__ import annotations

from rowfold.queries import descriptive, learning, operators, regression, text

MODULES = (regression, learning, descriptive, text, operators)


def all_queries() -> dict:
    return {k: v for m in MODULES for k, v in m.QUERIES.items()}


def all_oracles() -> dict[str, str]:
    return {k: v for m in MODULES for k, v in m.ORACLE.items()}
