"""Queries of the training-data operators and their SQL."""

from __future__ import annotations

import importlib

MODULES = ("lm_scoring", "chat_format", "ngram_join", "mixing", "sharding", "line_dedup", "decontamination", "ann", "token_output", "quality")


def _all(what: str) -> dict:
    out: dict = {}
    for m in MODULES:
        out |= getattr(importlib.import_module(f"{__package__}.{m}"), what)
    return out


def queries() -> dict:
    return _all("QUERIES")


def oracle_sql() -> dict[str, str]:
    return _all("ORACLES")
