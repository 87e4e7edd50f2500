"""Accuracy of recoveries, convergence and speed of runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treesketch.functions.fixedpoint import micro, wide


def estimate_error(est: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: n, max_error, median_error, l2sq of the truth, and the largest error in millionths of the norm."""
    both = est.select("coord", "est").join(truth.select("coord", "val"), "coord", "outer")
    error = F.abs(F.coalesce("est", F.lit(0)) - F.coalesce("val", F.lit(0)))
    val = wide(F.coalesce("val", F.lit(0)))
    found = both.select(error.alias("e"), (val * val).alias("sq")).agg(F.count(F.lit(1)).alias("n"), F.max("e").alias("max_error"), F.percentile("e", 0.5).alias("median_error"), F.sum("sq").cast("long").alias("l2sq"))
    return found.select("n", "max_error", micro(F.col("median_error")).alias("median_error_micro"), "l2sq", micro(F.col("max_error") / F.sqrt(F.col("l2sq").cast("double"))).alias("max_error_of_norm_micro"))


def heavy_recall(support: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(heavy, found): coordinates with val^2 k >= |val|^2 in truth, and how many of them the support has."""
    v = wide(F.col("val"))
    total = truth.agg(F.sum(v * v).alias("l2"))
    heavy = truth.crossJoin(F.broadcast(total)).where(v * v * k >= F.col("l2")).select("coord")
    marked = heavy.join(support.select("coord", F.lit(1).alias("hit")), "coord", "left")
    return marked.agg(F.count(F.lit(1)).alias("heavy"), F.count("hit").alias("found"))


def support_overlap(support: DataFrame, top: DataFrame) -> DataFrame:
    """(both, only_support, only_top) of two sets of coordinates."""
    a, b = support.select("coord", F.lit(1).alias("a")), top.select("coord", F.lit(1).alias("b"))
    j = a.join(b, "coord", "outer")
    return j.agg(F.count_if(F.col("a").isNotNull() & F.col("b").isNotNull()).alias("both"), F.count_if(F.col("b").isNull()).alias("only_support"), F.count_if(F.col("a").isNull()).alias("only_top"))


def captured_energy(support: DataFrame, truth: DataFrame) -> DataFrame:
    """(rank, coord, exact, captured_micro): the share of |truth|^2 in the support's first ranks, by |exact|. The support has k rows at most."""
    v = wide(F.col("val"))
    total = truth.agg(F.sum(v * v).alias("l2"))
    joined = support.select("coord").join(truth.select("coord", "val"), "coord", "left").select("coord", F.coalesce("val", F.lit(0)).alias("exact"))
    order = Window.orderBy(F.abs("exact").desc(), "coord")
    e = wide(F.col("exact"))
    ranked = joined.select(F.row_number().over(order).alias("rank"), "coord", "exact", F.sum(e * e).over(order.rowsBetween(Window.unboundedPreceding, 0)).alias("s"))
    return ranked.crossJoin(F.broadcast(total)).select("rank", "coord", "exact", micro(F.col("s").cast("double") / F.col("l2").cast("double")).alias("captured_micro"))


def compression_ratio(d: int, sent: DataFrame) -> DataFrame:
    """(method, values, ratio_micro): d over the values a worker sends, from rows (method, values)."""
    return sent.select("method", "values", micro(F.lit(float(d)) / F.col("values")).alias("ratio_micro"))


def comm_share(trace: DataFrame) -> DataFrame:
    """Per method the share of communication, and of compression, in the time of a step."""
    total = F.sum(F.col("t_compute") + F.col("t_compress") + F.col("t_comm"))
    return trace.groupBy("method").agg((F.sum("t_comm") / total).alias("comm_share"), (F.sum("t_compress") / total).alias("compress_share"))


def throughput(trace: DataFrame) -> DataFrame:
    """Examples a second per model and method."""
    return trace.groupBy("model", "method").agg((F.sum("examples") / F.sum("seconds")).alias("examples_per_s"))


def speedup(rates: DataFrame, method: str, over: str) -> DataFrame:
    """Ratio of two methods' rates, per model, from rows (model, method, examples_per_s)."""
    a = rates.where(F.col("method") == method).select("model", F.col("examples_per_s").alias("a"))
    b = rates.where(F.col("method") == over).select("model", F.col("examples_per_s").alias("b"))
    return a.join(b, "model").select("model", F.lit(method).alias("method"), F.lit(over).alias("over"), (F.col("a") / F.col("b")).alias("speedup"))


def mean_speedup(ratios: DataFrame) -> DataFrame:
    return ratios.groupBy("method", "over").agg(F.avg("speedup").alias("mean_speedup"))


def scaling_efficiency(rates: DataFrame) -> DataFrame:
    """thr(P) / (P thr(1)) from rows (method, workers, examples_per_s)."""
    one = rates.where(F.col("workers") == 1).select("method", F.col("examples_per_s").alias("one"))
    return rates.join(one, "method").select("method", "workers", (F.col("examples_per_s") / (F.col("workers") * F.col("one"))).alias("efficiency"))


def curve(trace: DataFrame) -> DataFrame:
    """Mean loss and last accuracy per method and epoch."""
    return trace.groupBy("method", "epoch").agg(F.avg("loss").alias("loss"), F.max_by("acc", "step").alias("acc"))


def epochs_to_converge(curves: DataFrame, tolerance: float) -> DataFrame:
    """Per method the first epoch from which the accuracy stays within ``tolerance`` of its last value."""
    rest = Window.partitionBy("method").orderBy("epoch").rowsBetween(0, Window.unboundedFollowing)
    whole = Window.partitionBy("method").orderBy("epoch").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    last = F.last("acc").over(whole)
    marked = curves.select("method", "epoch", (F.abs(F.col("acc") - last)).alias("off")).select("method", "epoch", F.max("off").over(rest).alias("worst"))
    return marked.where(F.col("worst") <= tolerance).groupBy("method").agg(F.min("epoch").alias("epoch"))
