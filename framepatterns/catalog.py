"""Registry of the engine's own queries and their SQL twins."""

from __future__ import annotations

_QUERIES: dict = {}
_ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    """Register a function (spark, directory) -> DataFrame under ``name``, with its DuckDB twin."""

    def keep(fn):
        _QUERIES[name] = fn
        if sql:
            _ORACLES[name] = sql
        return fn

    return keep


def _load() -> None:
    from framepatterns.workloads import experiments, measures, operators, surface  # noqa: F401  each registers its queries


def queries() -> dict:
    _load()
    return dict(_QUERIES)


def oracles() -> dict[str, str]:
    _load()
    return dict(_ORACLES)
