"""Where queries and their SQL are put down by name."""

from __future__ import annotations

from collections.abc import Callable


class Registry:
    def __init__(self) -> None:
        self.queries: dict[str, Callable] = {}
        self.sql: dict[str, str] = {}

    def add(self, name: str, sql: str | None = None):
        def put(f: Callable) -> Callable:
            if name in self.queries:
                raise ValueError(f"query {name} is there twice")
            self.queries[name] = f
            if sql is not None:
                self.sql[name] = sql
            return f

        return put
