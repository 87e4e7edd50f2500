"""Exact mode: values as whole multiples of a unit, so that sums do not depend on their order."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fractions of one in real values that are kept in exact mode.
UNIT = 1 << 20


def cents(amount: Column) -> Column:
    return F.floor(amount * 100 + 0.5).cast("long")


def to_fixed(value: Column, unit: int = UNIT) -> Column:
    """The nearest whole multiple; halves go up, in Spark and in DuckDB."""
    return F.floor(value * unit + 0.5).cast("long")


def from_fixed(value: Column, unit: int = UNIT) -> Column:
    return value / unit


def micro(value: Column) -> Column:
    """A measure as a whole number of millionths, for exact comparison."""
    return F.floor(value * 1_000_000 + 0.5).cast("long")


def wide(value: Column) -> Column:
    """Room for squares of BIGINT values."""
    return value.cast("decimal(38,0)")
