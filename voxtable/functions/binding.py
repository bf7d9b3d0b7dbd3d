"""Binding a value once inside an expression."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with value computed once for each row: lambdas would otherwise compute what they capture for every element."""
    return F.transform(F.array(value), body)[0]
