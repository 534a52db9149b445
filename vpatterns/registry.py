"""Queries and oracles of the pattern engine."""

from __future__ import annotations

from vpatterns.queries import ORACLES, QUERIES, mine, prep, relational, similar, sql, streams  # noqa: F401


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
