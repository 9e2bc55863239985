"""Queries over the given tables and their SQL oracles, by family."""

from __future__ import annotations

import importlib

FAMILIES = ["methods", "plans", "relational", "engine"]


def _merged(attribute: str) -> dict:
    found: dict = {}
    for family in FAMILIES:
        found |= getattr(importlib.import_module(f"{__name__}.{family}"), attribute)
    return found


def queries() -> dict:
    return _merged("QUERIES")


def oracle_sql() -> dict:
    return _merged("ORACLES")
