"""Registered queries: each a callable (spark, sf_dir) and, where SQL can say it, its SQL."""

from __future__ import annotations

REGISTRY: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        key = name or f.__name__
        if key in REGISTRY:
            raise ValueError(f"two queries named {key}")
        REGISTRY[key] = f
        if sql:
            SQL[key] = sql
        return f

    return add


def _load() -> None:
    from tierbit.catalog import methods, surround, workloads  # noqa: F401


def queries() -> dict:
    _load()
    return dict(REGISTRY)


def oracle_sql() -> dict[str, str]:
    _load()
    return dict(SQL)
