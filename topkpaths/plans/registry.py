"""All queries of the library, and their SQL twins."""

from __future__ import annotations

import importlib

_MODULES = ["topkpaths.plans.graph_queries", "topkpaths.plans.path_queries", "topkpaths.plans.workloads", "topkpaths.operators.relational", "topkpaths.operators.scalars", "topkpaths.functions.queries", "topkpaths.sources.queries", "topkpaths.streaming.queries"]


def _collect(what: str) -> dict:
    out: dict = {}
    for name in _MODULES:
        out |= getattr(importlib.import_module(name), what)
    return out


def queries() -> dict:
    return _collect("QUERIES")


def oracles() -> dict:
    return _collect("ORACLES")
