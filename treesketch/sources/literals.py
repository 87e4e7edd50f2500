"""Small tables of constants that stay in the JVM: one task, no Python rows."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def literal_rows(spark: SparkSession, rows: Sequence[tuple], schema: str) -> DataFrame:
    """``rows`` as a one-partition table; ``schema`` is 'name type, name type'."""
    fields = [f.split() for f in schema.split(", ")]
    one = spark.range(0, 1, 1, 1)
    if not rows:
        return one.where(F.lit(False)).select(*[F.lit(None).cast(t).alias(n) for n, t in fields])
    cells = [F.struct(*[F.lit(v).cast(t).alias(n) for v, (n, t) in zip(row, fields)]) for row in rows]
    return one.select(F.inline(F.array(*cells)))


def literal_grid(spark: SparkSession, **columns: Sequence[int]) -> DataFrame:
    """Every combination of the columns' whole numbers."""
    out = spark.range(0, 1, 1, 1).select()
    for name, values in columns.items():
        out = out.select("*", F.explode(F.array(*[F.lit(v).cast("long") for v in values])).alias(name))
    return out
