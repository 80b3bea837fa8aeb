"""Named queries of every method, measure and operator, with DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from gradvb.queries import estimates, experiments, relations, steps

MODULES = (estimates, steps, experiments, relations)


def queries() -> dict:
    return {name: f for module in MODULES for name, f in module.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for module in MODULES for name, sql in module.SQL.items()}
