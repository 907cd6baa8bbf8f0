"""Queries over the given tables, by name, and their SQL counterparts."""

from __future__ import annotations

from . import queries_core, queries_experiments, queries_measures, queries_ops


def queries() -> dict:
    return {**queries_core.QUERIES, **queries_measures.QUERIES, **queries_ops.QUERIES, **queries_experiments.QUERIES}


def oracle_sql() -> dict[str, str]:
    return {**queries_core.SQL, **queries_measures.SQL, **queries_ops.SQL, **queries_experiments.SQL}
