"""The book of queries: every query by name, and the SQL of those that have one."""

from __future__ import annotations

from pyspark.sql import functions as F

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    """Enter a function of (spark, sf_dir) under a name."""

    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


def rounded(*names: str, places: int = 6):
    return [F.round(F.col(n), places).alias(n) for n in names]
