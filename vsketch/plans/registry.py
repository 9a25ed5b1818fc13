"""Registration of queries with their SQL."""

from __future__ import annotations

from collections.abc import Callable


def registry() -> tuple[dict, dict, Callable]:
    queries: dict = {}
    sql: dict = {}

    def add(name: str, run: Callable, text: str | None = None) -> None:
        if name in queries:
            raise ValueError(f"{name} is registered twice")
        queries[name] = run
        if text is not None:
            sql[name] = text

    return queries, sql, add
