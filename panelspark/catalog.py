"""All queries of the engine and their SQL oracles."""

from __future__ import annotations

import importlib

MODULES = ("mesh", "packing", "trees", "compression", "problems", "streams", "relational")


def _all(what: str) -> dict:
    out = {}
    for m in MODULES:
        out |= getattr(importlib.import_module(f"panelspark.workloads.{m}").R, what)
    return out


def queries() -> dict:
    return _all("queries")


def oracle_sql() -> dict:
    return _all("sql")
