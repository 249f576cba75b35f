"""Named queries over the given tables, and the SQL that each is compared with."""

from __future__ import annotations

from . import costs, experiments, operators, solvers, steps, surface, tensors

MODULES = (tensors, steps, solvers, experiments, costs, operators, surface)


def queries() -> dict:
    return {name: run for module in MODULES for name, run in module.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for module in MODULES for name, sql in module.ORACLE_SQL.items()}
