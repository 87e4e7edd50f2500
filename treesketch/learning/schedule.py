"""Shards, mini-batches and the warm-up schedule."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from treesketch.functions.hashing import fill_order
from treesketch.sources.literals import literal_rows

# Fixed values of the warm-up: densities in millionths and rates in thousandths of the first epochs.
WARMUP_DENSITIES_PPM = (250_000, 72_500, 15_000, 4_000)
WARMUP_RATES_PERMILLE = (100, 30, 10)


def worker_of(key: Column, workers: int, seed: int = 0) -> Column:
    """A random but fixed shard of each key."""
    return (fill_order(F.pmod(key, F.lit((1 << 31) - 1)), seed, 0) % workers).cast("int")


def minibatch(examples: DataFrame, step: int, batch: int, seed: int = 0) -> DataFrame:
    """``batch`` rows of each worker, by a hash of (seed, step, key): the same whatever the partitioning."""
    order = Window.partitionBy("worker").orderBy(fill_order(F.pmod("key", F.lit((1 << 31) - 1)), seed, step), "key")
    return examples.withColumn("rn", F.row_number().over(order)).where(F.col("rn") <= batch).drop("rn")


def warmup_schedule(spark: SparkSession, epochs: int | DataFrame, d: int, base_k: int, base_rate_permille: int) -> DataFrame:
    """SCHEDULE(epoch, density_ppm, rate_permille, k) with two step functions of the epoch.

    k = max(1, ceil(density d)) in the warm-up and ``base_k`` after it; the last
    warm-up rate is held to the end of the warm-up densities. ``epochs`` is their
    number, or a table with a column epoch.
    """
    steps = [(e, WARMUP_DENSITIES_PPM[e], WARMUP_RATES_PERMILLE[min(e, len(WARMUP_RATES_PERMILLE) - 1)]) for e in range(len(WARMUP_DENSITIES_PPM))]
    steps.append((len(WARMUP_DENSITIES_PPM), None, base_rate_permille))
    known = literal_rows(spark, steps, "since int, density_ppm long, rate_permille long")
    all_epochs = epochs.select("epoch") if isinstance(epochs, DataFrame) else spark.range(epochs).select(F.col("id").cast("int").alias("epoch"))
    # as-of lookup: the last step at or before each epoch
    latest = all_epochs.join(F.broadcast(known), F.col("since") <= F.col("epoch")).groupBy("epoch").agg(F.max_by(F.struct("density_ppm", "rate_permille"), "since").alias("s"))
    k = F.when(F.col("s.density_ppm").isNull(), F.lit(base_k)).otherwise(F.greatest(F.lit(1), F.floor((F.lit(d).cast("long") * F.col("s.density_ppm") + 999_999) / 1_000_000)))
    return latest.select("epoch", F.col("s.density_ppm").alias("density_ppm"), F.col("s.rate_permille").alias("rate_permille"), k.cast("long").alias("k"))


def schedule_at(epoch: int, d: int, base_k: int, base_rate: float, warmup: bool) -> tuple[int, float]:
    """(k, rate) of an epoch, as the table has them."""
    if not warmup or epoch >= len(WARMUP_DENSITIES_PPM):
        return base_k, base_rate
    k = max(1, (d * WARMUP_DENSITIES_PPM[epoch] + 999_999) // 1_000_000)
    return k, WARMUP_RATES_PERMILLE[min(epoch, len(WARMUP_RATES_PERMILLE) - 1)] / 1000
