"""Registered queries: name -> builder, and the DuckDB SQL that must give the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Builder = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Builder] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Builder], Builder]:
    """Registers a query under its name, with its SQL unless SQL cannot express it."""

    def add(build: Builder) -> Builder:
        QUERIES[name] = build
        if sql:
            ORACLES[name] = sql
        return build

    return add
