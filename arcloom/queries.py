"""All queries of the graph engine and their SQL."""

from __future__ import annotations

import importlib

MODULES = ("operators.generate", "operators.search", "operators.spectral", "operators.coalesce", "operators.metrics", "operators.grouping", "operators.baselines", "operators.represent", "sources.ingest", "sources.io", "operators.relational", "functions.queries", "streaming.edges", "suite")


def _all(what: str) -> dict:
    out: dict = {}
    for m in MODULES:
        out |= getattr(importlib.import_module(f"arcloom.{m}"), what)
    return out


def queries() -> dict:
    return _all("QUERIES")


def oracle_sql() -> dict[str, str]:
    return _all("ORACLES")
