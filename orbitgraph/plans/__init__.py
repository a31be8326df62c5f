"""Named queries and their SQL twins."""

from __future__ import annotations

import importlib

MODULES = ("core", "physics", "runtime", "learning", "scaling", "workloads", "shells")


def _all(what: str) -> dict:
    out: dict = {}
    for name in MODULES:
        out |= getattr(importlib.import_module(f"{__name__}.{name}"), what)
    return out


def queries() -> dict:
    return _all("QUERIES")


def oracles() -> dict:
    return _all("SQL")
