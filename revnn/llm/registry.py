"""Queries of this subpackage and their SQL, for the entry point."""

from __future__ import annotations

from importlib import import_module
from pkgutil import iter_modules

import revnn.llm as here

MODULES = [import_module(f"revnn.llm.{m.name}") for m in sorted(iter_modules(here.__path__), key=lambda m: m.name) if m.name.startswith("op")]


def queries() -> dict:
    return {name: f for m in MODULES for name, f in m.QUERIES.items()}


def oracle_sql() -> dict:
    return {name: sql for m in MODULES for name, sql in getattr(m, "ORACLE_SQL", {}).items()}
