"""The other ways to send a vector: whole, its largest entries, random entries, few bits."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treesketch.operators.recovery import THRESHOLD_K, _top, drawn_first, magnitude_bin
from treesketch.operators.topology import rounds


def dense_sum(coords: DataFrame) -> DataFrame:
    """(coord, val) summed over all workers."""
    return coords.groupBy("coord").agg(F.sum("val").alias("val")).where(F.col("val") != 0)


def exact_topk(coords: DataFrame, k: int) -> DataFrame:
    """The k largest of the dense sum: the truth that recoveries are held against."""
    return _top(dense_sum(coords), [F.abs("val").desc(), F.col("coord")], k, F.abs("val"))


def local_topk(coords: DataFrame, k: int) -> DataFrame:
    """Each worker's k largest |val|; ties to the smaller coordinate.

    Up to ``THRESHOLD_K`` Spark's window limits each task's rows before the
    shuffle. Beyond it a histogram of magnitudes for each worker, some hundred
    rows, sets the cut; only the rows of one bin of a worker are ordered.
    """
    order = [F.abs("val").desc(), F.col("coord")]
    summed = coords.groupBy("worker", "coord").agg(F.sum("val").alias("val")).where(F.col("val") != 0)
    if k <= THRESHOLD_K:
        return summed.withColumn("rn", F.row_number().over(Window.partitionBy("worker").orderBy(*order))).where(F.col("rn") <= k).drop("rn")
    binned = summed.withColumn("_bin", magnitude_bin(F.abs("val")))
    down = Window.partitionBy("worker").orderBy(F.col("_bin").desc())
    counts = binned.groupBy("worker", "_bin").agg(F.count(F.lit(1)).alias("n")).withColumn("upto", F.sum("n").over(down))
    cut = counts.where(F.col("upto") > k).groupBy("worker").agg(F.max("_bin").alias("_last"), F.max_by(F.lit(k) - F.col("upto") + F.col("n"), "_bin").alias("_room"))
    marked = binned.join(F.broadcast(cut), "worker", "left")  # a row for each worker
    whole = marked.where(F.col("_last").isNull() | (F.col("_bin") > F.col("_last"))).select(*summed.columns)
    rest = marked.where(F.col("_bin") == F.col("_last")).withColumn("rn", F.row_number().over(Window.partitionBy("worker").orderBy(*order)))
    return whole.unionByName(rest.where(F.col("rn") <= F.col("_room")).select(*summed.columns))


def star_topk(coords: DataFrame, k: int) -> DataFrame:
    """Local top-k gathered and summed at one server."""
    return dense_sum(local_topk(coords, k))


def tree_topk(coords: DataFrame, k: int, workers: int) -> DataFrame:
    """Local top-k merged along the halving tree, each merge cut to its k largest again.

    A re-selection needs a participant's whole vector together, so each round shuffles, at most workers * k rows.
    """
    now = local_topk(coords, k).select(F.col("worker").cast("long").alias("worker"), "coord", "val")
    for _ in range(rounds(workers)):
        now = local_topk(now.withColumn("worker", F.shiftright("worker", 1)), k)
    return now.select("coord", "val")


def random_k(coords: DataFrame, k: int, seed: int = 1, step: int = 1) -> DataFrame:
    """The dense sum on k of its coordinates in the shared random order."""
    return drawn_first(dense_sum(coords), k, seed, step)


def quantize(coords: DataFrame, bits: int) -> DataFrame:
    """Each worker's values as ``bits``-bit signed levels of its largest magnitude: (worker, coord, level, val)."""
    if not 2 <= bits <= 31:
        raise ValueError("bits must lie in 2 .. 31")
    top = (1 << (bits - 1)) - 1
    largest = coords.groupBy("worker").agg(F.max(F.abs("val")).cast("double").alias("m"))
    level = F.floor(F.col("val") / F.col("m") * top + 0.5).cast("long")
    rows = coords.join(largest, "worker").where(F.col("m") > 0)
    return rows.select("worker", "coord", level.alias("level"), (level * F.col("m") / top).alias("val"))


def builtin_top(df: DataFrame, column: str, k: int) -> DataFrame:
    """Spark's own frequency sketch, for contrast: counts only, no signed values. (item, n)"""
    found = df.agg(F.approx_top_k(column, F.lit(k)).alias("t")) if hasattr(F, "approx_top_k") else df.selectExpr(f"approx_top_k({column}, {k}) AS t")
    return found.select(F.explode("t").alias("t")).select(F.col("t.item").alias("item"), F.col("t.count").alias("n"))
