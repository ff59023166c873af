"""The relational surface around the join: each operator once, on the given tables, with its DuckDB statement."""

from __future__ import annotations

from . import aggregation, functions, relational, windows

_PARTS = (relational, aggregation, windows, functions)


def queries():
    return {name: make for part in _PARTS for name, (make, _) in part.OPERATORS.items()}


def oracle_sql():
    return {name: sql for part in _PARTS for name, (_, sql) in part.OPERATORS.items() if sql is not None}
