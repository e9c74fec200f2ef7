"""Queries and their SQL, a module for each part of the inventory."""

from __future__ import annotations

import importlib

#: Modules of this folder that hold QUERIES and ORACLE_SQL.
PARTS: tuple[str, ...] = ("method_queries", "operator_queries", "workload_queries")


def _merged(name: str) -> dict:
    found: dict = {}
    for part in PARTS:
        found |= getattr(importlib.import_module(f"{__name__}.{part}"), name)
    return found


def queries() -> dict:
    return _merged("QUERIES")


def oracle_sql() -> dict:
    return _merged("ORACLE_SQL")


def flagship(spark, sf_dir: str):
    from rangecut.catalog import method_queries

    return method_queries.flagship(spark, sf_dir)
