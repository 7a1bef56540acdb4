"""All queries and their oracles, from the modules of this package."""

from __future__ import annotations

from caregraph.queries import graph, link, ops, text, work

MODULES = (graph, link, work, ops, text)


def queries() -> dict:
    out: dict = {}
    for m in MODULES:
        out |= m.QUERIES
    return out


def oracle_sql() -> dict[str, str]:
    out: dict[str, str] = {}
    for m in MODULES:
        out |= m.SQL
    return out
