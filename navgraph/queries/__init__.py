"""All registered queries of the reference's methods and operators, and their SQL."""

from __future__ import annotations

from importlib import import_module

MODULES = ("methods", "relational", "indexed")


def queries() -> dict:
    return {k: f for m in MODULES for k, f in import_module(f"navgraph.queries.{m}").QUERIES.items()}


def oracle_sql() -> dict:
    return {k: s for m in MODULES for k, s in import_module(f"navgraph.queries.{m}").SQL.items()}
