"""All queries of the engine by name, with the SQL that DuckDB runs beside them.

A query is (spark, sf_dir) -> DataFrame. Methods whose result SQL cannot give (matching, iteration, hulls, timing)
have none and are tested by certificates and brute force.
"""

from __future__ import annotations

from collections.abc import Callable

from regioncount.plans import q_core, q_relational, q_workloads


def _all() -> dict[str, tuple[Callable, str | None]]:
    return q_core.QUERIES | q_workloads.QUERIES | q_relational.QUERIES


def queries() -> dict[str, Callable]:
    return {name: run for name, (run, _) in _all().items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in _all().items() if sql}
