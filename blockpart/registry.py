"""Queries of all groups, and the SQL that judges them."""

from __future__ import annotations

from blockpart.queries import measures, model, relational

GROUPS = (model, measures, relational)


def queries() -> dict:
    return {k: v[0] for g in GROUPS for k, v in g.QUERIES.items()}


def oracle_sql() -> dict:
    return {k: v[1] for g in GROUPS for k, v in g.QUERIES.items() if v[1]}
