"""Queries and oracle SQL of the engine's own operators, by key."""

from __future__ import annotations

from importlib import import_module

MODULES = ("search_queries", "hybrid_queries", "update_queries", "relational_queries")


def _modules():
    return [import_module(f"ivfspark.catalog.{name}") for name in MODULES]


def queries() -> dict:
    return {name: fn for module in _modules() for name, fn in module.QUERIES_BY_KEY.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for module in _modules() for name, sql in module.SQL.items()}
