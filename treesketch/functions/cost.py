"""Modelled time of an exchange: alpha for a message, beta for a value."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from treesketch.sources.literals import literal_grid

METHODS = ("dense", "star_topk", "tree_topk", "star_sketch", "tree_sketch")


def message(values: Column, alpha: Column, beta: Column) -> Column:
    return alpha + values * beta


def tree_rounds(workers: Column) -> Column:
    """ceil(log2(workers)) without rounding errors: the bits of workers - 1."""
    return F.when(workers <= 1, F.lit(0)).otherwise(F.length(F.bin(workers - 1))).cast("long")


def predict(method: str, *, workers: Column, d: Column, k: Column, size: Column, alpha: Column, beta: Column, exact_round: bool = True) -> Column:
    """Critical-path time of one all-reduce; ``exact_round=False`` leaves out the second exchange of exact values."""
    r = tree_rounds(workers)
    if method == "dense":
        return 2 * r * message(d, alpha, beta)
    if method == "tree_topk":
        return 2 * r * message(2 * k, alpha, beta)
    if method == "star_topk":
        return workers * message(2 * k, alpha, beta) + workers * message(2 * k * workers, alpha, beta)
    second = message(k, alpha, beta) if exact_round else F.lit(0).cast("long")
    if method == "star_sketch":
        return 2 * workers * (message(size, alpha, beta) + second)
    if method == "tree_sketch":
        return 2 * r * (message(size, alpha, beta) + second)
    raise ValueError(f"unknown method {method}")


def grid(spark: SparkSession, *, workers: list[int], dims: list[int] | DataFrame, densities_ppm: list[int], alphas: list[int], rows: int = 5, width_ppm: int = 10_000) -> DataFrame:
    """Every combination with beta = 1: (workers, d, k, size, alpha, method, t, t_paper).

    k = max(1, ceil(density d)); the width is ``width_ppm`` millionths of d, 256
    at least; ``t_paper`` leaves the exact round out. All whole numbers. ``dims``
    may be a table with a column d.
    """

    base = literal_grid(spark, workers=workers, ppm=densities_ppm, alpha=alphas)
    base = base.crossJoin(dims.select("d").distinct() if isinstance(dims, DataFrame) else literal_grid(spark, d=dims))
    k = F.greatest(F.lit(1).cast("long"), F.floor((F.col("d") * F.col("ppm") + 999_999) / 1_000_000).cast("long"))
    size = rows * F.greatest(F.lit(256).cast("long"), F.floor(F.col("d") * width_ppm / 1_000_000).cast("long"))
    base = base.select("workers", "d", k.alias("k"), size.alias("size"), "alpha").distinct()
    args = {c: F.col(c) for c in ("workers", "d", "k", "size", "alpha")} | {"beta": F.lit(1).cast("long")}
    each = [F.struct(F.lit(m).alias("method"), predict(m, **args).alias("t"), predict(m, **args, exact_round=False).alias("t_paper")) for m in METHODS]
    return base.select("workers", "d", "k", "size", "alpha", F.inline(F.array(*each)))


def tree_sketch_wins(k: Column, size: Column, alpha: Column, beta: Column) -> Column:
    """Whether the modelled tree-sketch time is below tree-top-k's: alpha < (k - size) beta."""
    return alpha < (k - size) * beta
