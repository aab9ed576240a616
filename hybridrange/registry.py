"""Collects the queries and oracles that the modules register."""

from __future__ import annotations

import importlib

MODULES: tuple[str, ...] = ("methods", "workloads", "relational", "streaming.queries", "sources.index_reader")


def _all(name: str) -> dict:
    out: dict = {}
    for m in MODULES:
        out |= getattr(importlib.import_module(f"hybridrange.{m}"), name)
    return out


def queries() -> dict:
    return _all("QUERIES")


def oracles() -> dict:
    return _all("ORACLES")
