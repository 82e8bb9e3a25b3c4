"""All queries of the selection engine, and their SQL."""

from __future__ import annotations

from .registry import QUERIES, SQL, Query


def queries() -> dict[str, Query]:
    from . import analysis, experiments, mining  # noqa: F401  they register themselves

    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    queries()
    return dict(SQL)
