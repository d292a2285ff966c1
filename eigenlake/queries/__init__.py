"""Registered queries: methods, measures, workloads and operators on the given tables, each with its SQL where there is one."""

from __future__ import annotations

from importlib import import_module

from .base import ORACLES, QUERIES

for _name in ("methods", "measures", "relational", "streams"):
    import_module(f"{__name__}.{_name}")

__all__ = ["ORACLES", "QUERIES"]
