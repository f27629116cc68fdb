"""Operators of a training-data pipeline. Nothing else in the library imports this subpackage."""

from __future__ import annotations

from importlib import import_module

_MODULES = ("exact_dedup", "warc_bundles", "source_mixing", "simhash_links", "pair_quality", "language_id", "packing", "sharding", "toxicity", "vector_search")


def _all(name: str) -> dict:
    found: dict = {}
    for module in _MODULES:
        found |= getattr(import_module(f"{__name__}.{module}"), name)
    return found


def queries() -> dict:
    return _all("QUERIES")


def oracle_sql() -> dict:
    return _all("SQL")
