"""Stored sketches: written once per partition of the data, merged later without the data."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treesketch.functions.hashing import SketchSpec


def write_sketch(sketch: DataFrame, path: str, spec: SketchSpec, *, partition_by: tuple[str, ...] = ("worker",), mode: str = "append") -> None:
    """Cells as Parquet, partitioned by worker, day or what else keys them; the spec goes along in each row as JSON (a constant column costs nothing)."""
    sketch.withColumn("spec", F.lit(spec.to_json())).write.mode(mode).partitionBy(*partition_by).parquet(path)


def read_sketch(spark: SparkSession, path: str, spec: SketchSpec | None = None) -> DataFrame:
    """Stored cells; a spec limits them to sketches that may be added to it."""
    cells = spark.read.parquet(path)
    if spec is not None:
        cells = cells.where(F.col("spec") == spec.to_json())
    return cells.drop("spec")


def write_trace(rows: list[dict], spark: SparkSession, path: str) -> None:
    """A run's trace or ledger, one row a step."""
    spark.createDataFrame(rows).write.mode("overwrite").parquet(path)
