"""One place where every query is registered with its oracle, so neither is forgotten."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
SECTIONS: dict[str, str] = {}


def query(name: str, section: str, oracle: str | None = None) -> Callable[[Query], Query]:
    """Registers a query; oracle is SQL for the same rows, None where SQL can't express them."""

    def add(fn: Query) -> Query:
        if name in QUERIES:
            raise ValueError(f"query {name} is registered twice")
        QUERIES[name], SECTIONS[name] = fn, section
        if oracle is not None:
            ORACLES[name] = oracle.strip()
        return fn

    return add


def load_all() -> None:
    """Imports every module that registers queries."""
    from treepack.queries import ALL  # noqa: F401
