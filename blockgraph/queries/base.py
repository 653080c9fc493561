"""Registration of queries beside their DuckDB twins, and SQL text that several twins share."""

from __future__ import annotations

from collections.abc import Callable

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None) -> Callable:
    def add(f: Callable) -> Callable:
        key = name or f.__name__
        if key in QUERIES:
            raise ValueError(f"two queries named {key}")
        QUERIES[key] = f
        if sql is not None:
            ORACLES[key] = sql
        return f

    return add


def xlogx_sql(x: str) -> str:
    return f"(CASE WHEN ({x}) > 0 THEN ({x}) * ln(CAST(({x}) AS DOUBLE)) ELSE 0 END)"


def cost_sql(hit: str, miss: str) -> str:
    return f"(CASE WHEN ({hit}) >= 0 AND ({miss}) >= 0 THEN {xlogx_sql(f'({hit}) + ({miss})')} - {xlogx_sql(hit)} - {xlogx_sql(miss)} ELSE 0 END)"
