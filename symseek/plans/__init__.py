"""Whole queries: the methods, baselines, measures and experiment workloads on the given tables."""

from __future__ import annotations


def queries() -> dict:
    from symseek.plans import methods, operators, workloads  # noqa: F401  they register their queries
    from symseek.plans.registry import QUERIES

    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    queries()
    from symseek.plans.registry import SQL

    return dict(SQL)
