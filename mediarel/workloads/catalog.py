"""Catalog of registered queries and their oracle SQL."""

from __future__ import annotations

from importlib import import_module

MODULES = ("points", "spans", "crosscam", "algebra", "relational")


def _gather(name: str) -> dict:
    found: dict = {}
    for module in MODULES:
        part = getattr(import_module(f"mediarel.workloads.{module}"), name)
        clash = found.keys() & part.keys()
        if clash:
            raise ValueError(f"queries registered twice: {sorted(clash)}")
        found.update(part)
    return found


def queries() -> dict:
    return _gather("QUERIES")


def oracle_sql() -> dict:
    return _gather("ORACLE_SQL")
