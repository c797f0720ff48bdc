"""All queries of the entropy engine, by name, with their SQL."""

from __future__ import annotations

from importlib import import_module

from ..registry import QUERIES, SQL

for _part in ("measures", "protocol", "structure", "collision", "baselines", "workloads", "claims", "relational", "functions", "streams", "surface"):
    try:
        import_module(f"{__name__}.{_part}")
    except ModuleNotFoundError as e:
        if e.name != f"{__name__}.{_part}":
            raise


def queries():
    return dict(QUERIES)


def oracle_sql():
    return dict(SQL)
