"""Registered queries and their DuckDB counterparts."""

from __future__ import annotations

_QUERIES: dict = {}
_ORACLES: dict = {}


def register(key: str, run, oracle: str | None = None) -> None:
    if key in _QUERIES:
        raise ValueError(f"query {key} is registered twice")
    _QUERIES[key] = run
    if oracle is not None:
        _ORACLES[key] = oracle


def _load() -> None:
    from pairsample.plans import queries as _, relational as _more  # noqa: F401


def queries() -> dict:
    _load()
    return dict(_QUERIES)


def oracle_sql() -> dict:
    _load()
    return dict(_ORACLES)
