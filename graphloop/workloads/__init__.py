"""Query keys of the graph engine: callables over (spark, sf_dir) and the DuckDB SQL they must equal."""

from __future__ import annotations

from graphloop.workloads import algebra, analytics, around, batch, expressive, functions, language, tasks

_PARTS = (analytics, language, batch, expressive, algebra, functions, around, tasks)


def queries() -> dict:
    return {name: f for part in _PARTS for name, f in part.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: text for part in _PARTS for name, text in part.SQL.items()}
