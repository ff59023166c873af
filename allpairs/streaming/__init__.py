"""The join's steps on streams of files; each query runs until all that is there has been read."""

from __future__ import annotations

from .events import OPERATORS


def queries():
    return {name: make for name, (make, _) in OPERATORS.items()}


def oracle_sql():
    return {name: sql for name, (_, sql) in OPERATORS.items() if sql is not None}
