"""Sparse vectors as maps from coordinate to value: the form in which a message travels in one row."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def to_map(coords: DataFrame, by: tuple[str, ...] = ("worker",)) -> DataFrame:
    """One row a group: ``vec map<coord, val>``. For sparse messages; a group's entries must fit a row."""
    summed = coords.groupBy(*by, "coord").agg(F.sum("val").alias("val")).where(F.col("val") != 0)
    return summed.groupBy(*by).agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("coord", "val")))).alias("vec"))


def from_map(vectors: DataFrame, column: str = "vec") -> DataFrame:
    others = [c for c in vectors.columns if c != column]
    return vectors.select(*others, F.explode(column).alias("coord", "val"))


def add(a: Column, b: Column) -> Column:
    """The sum of two sparse vectors; entries that cancel go."""
    both = F.map_zip_with(a, b, lambda _, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0)))
    return F.map_filter(both, lambda _, v: v != 0)


def top(vec: Column, k: int) -> Column:
    """The k entries of largest magnitude, ties to the smaller coordinate."""
    ranked = F.array_sort(F.transform(F.map_entries(vec), lambda e: F.struct((-F.abs(e["value"])).alias("m"), e["key"].alias("key"), e["value"].alias("value"))))
    return F.map_from_entries(F.transform(F.slice(ranked, 1, k), lambda e: F.struct(e["key"], e["value"])))
