"""Registry of the core queries: name -> (query, oracle SQL or None)."""

from __future__ import annotations

_QUERIES: dict = {}
_ORACLES: dict = {}


def register(name: str, fn, sql: str | None = None) -> None:
    """Add one query; a name may be registered once."""
    if name in _QUERIES:
        raise ValueError(f"query {name} is registered twice")
    _QUERIES[name] = fn
    if sql is not None:
        _ORACLES[name] = sql


def queries() -> dict:
    return dict(_QUERIES)


def oracle_sql() -> dict:
    return dict(_ORACLES)
