"""Queries and SQL of the subpackage, by name."""

from __future__ import annotations

from . import exact_dedup, langid, mixing, near_dedup, packing, sharding, suffix_dedup, topk, toxicity, url_filter

MODULES = (mixing, packing, topk, url_filter, near_dedup, sharding, toxicity, suffix_dedup, langid, exact_dedup)


def queries() -> dict:
    return {name: f for m in MODULES for name, f in m.QUERIES.items()}


def oracle_sql() -> dict:
    return {name: sql for m in MODULES for name, sql in m.ORACLES.items()}
