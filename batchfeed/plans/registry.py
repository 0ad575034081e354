"""Registration of queries: a callable, and SQL for DuckDB where SQL can express it."""

from __future__ import annotations

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    """Register the decorated (spark, sf_dir) -> DataFrame."""

    def add(f):
        if name in QUERIES:
            raise ValueError(f"{name} is taken")
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add
