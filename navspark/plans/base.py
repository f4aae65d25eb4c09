"""Where queries and their SQL twins are collected."""

from __future__ import annotations

from collections.abc import Callable

from navspark.sources.carriers import with_views

QUERIES: dict[str, Callable] = {}
ORACLE: dict[str, str] = {}


def query(name: str, sql: str | None = None, **views: str):
    """Register a query; ``sql`` is its twin for DuckDB and may name the carrier views."""

    def put(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE[name] = with_views(sql, **views)
        return f

    return put
