"""Queries of the graph engine and their SQL, by name."""

from __future__ import annotations

from . import extras, measures, relational, workloads

MODULES = (workloads, extras, relational, measures)


def queries() -> dict:
    return {name: f for m in MODULES for name, f in m.QUERIES.items()}


def oracle_sql() -> dict:
    return {name: sql for m in MODULES for name, sql in m.ORACLES.items()}
