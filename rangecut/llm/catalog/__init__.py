"""Queries of the training-data operators and their SQL, a module for each."""

from __future__ import annotations

import importlib

PARTS = ("chat_queries", "url_queries", "quality_queries", "toxicity_queries", "packing_queries", "mixing_queries", "jaccard_queries", "html_queries", "nn_queries")


def _merged(name: str) -> dict:
    found: dict = {}
    for part in PARTS:
        found |= getattr(importlib.import_module(f"{__name__}.{part}"), name)
    return found


def queries() -> dict:
    return _merged("QUERIES")


def oracle_sql() -> dict:
    return _merged("ORACLE_SQL")
