"""The queries and, where SQL can say them, their oracles, side by side."""

from __future__ import annotations

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    """Register a callable (spark, sf_dir) -> DataFrame, and its DuckDB SQL."""

    def put(f):
        if name in QUERIES:
            raise ValueError(f"{name} twice")
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put
