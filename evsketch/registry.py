"""All queries of the distinct-counting engine, with their oracles."""

from __future__ import annotations

from importlib import import_module

from evsketch.workloads.common import ORACLES, QUERIES

for _name in ("methods", "baselines", "measures", "scenarios", "relational", "streams", "functions"):
    import_module(f"evsketch.workloads.{_name}")


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict:
    return dict(ORACLES)
