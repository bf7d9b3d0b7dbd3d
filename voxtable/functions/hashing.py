"""Seeded decisions: prefixes of md5 over joined keys, the same in every engine, run and partitioning."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _text(key: Column | str) -> Column:
    return F.lit(key) if isinstance(key, str) else key.cast("string")


def draw(*keys: Column | str) -> Column:
    """A number from 0 to 2**32 - 1; plain strings are seeds, columns are keys."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *map(_text, keys))), 1, 8), 16, 10).cast("bigint")


def uniform(*keys: Column | str) -> Column:
    """Strictly between 0 and 1."""
    return (draw(*keys) + F.lit(0.5)) / F.lit(4294967296.0)


def sql_draw(*keys: str) -> str:
    """The same number in DuckDB; keys are SQL expressions."""
    return f"('0x' || substr(md5(concat_ws('|', {', '.join(keys)})), 1, 8))::BIGINT"


def sql_uniform(*keys: str) -> str:
    return f"(({sql_draw(*keys)} + 0.5::DOUBLE) / 4294967296.0::DOUBLE)"
