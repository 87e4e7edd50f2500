"""Reading the support of an update out of a summed sketch, and fetching its exact values."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from treesketch.functions.fixedpoint import wide
from treesketch.functions.hashing import PRIME, SketchSpec, fill_order
from treesketch.operators import sketch as sk

#: Beyond this k the driver's merge of all tasks' first k rows would be the bottleneck; a threshold is found first.
THRESHOLD_K = 1_000
#: Bins of the shared random order, of equal width.
FILL_BINS = 1 << 12


def split_heavy(est: DataFrame, l2: DataFrame, k: int, *, literal_signed: bool = False) -> DataFrame:
    """ESTIMATE with ``heavy``: est^2 * k >= l2sq, without division.

    ``literal_signed`` compares the signed estimate itself, est * k >= l2sq:
    negative coordinates are never heavy then. For the ablation only.
    """
    return _split(est.crossJoin(F.broadcast(l2)), k, literal_signed)


def _split(both: DataFrame, k: int, literal_signed: bool) -> DataFrame:
    exact = dict(both.dtypes)["est"] not in ("double", "float")
    e = wide(F.col("est")) if exact else F.col("est")
    left = e * F.lit(k) if literal_signed else e * e * F.lit(k)
    return both.select("coord", "est", (left >= F.col("l2sq")).alias("heavy"))


def magnitude_bin(size: Column) -> Column:
    """A number that does not fall as ``size`` grows: eighths of powers of two, some hundred values on data."""
    return F.floor(F.log2(F.greatest(size.cast("double"), F.lit(1e-300))) * 8).cast("int")


def _first(df: DataFrame, order: list[Column], k: int, bin_: Column) -> DataFrame:
    """The first k rows in an order that ``bin_`` descending agrees with.

    For a large k a histogram of the bins (a few thousand rows at most) tells
    which rows are surely in; only the rest of one bin is sorted.
    """
    if k <= THRESHOLD_K:
        return df.orderBy(*order).limit(k)
    binned = df.withColumn("_bin", bin_)
    counts = {r["_bin"]: r["n"] for r in binned.groupBy("_bin").agg(F.count(F.lit(1)).alias("n")).collect()}
    sure, last = 0, None
    for b in sorted(counts, reverse=True):
        if sure + counts[b] > k:
            last = b
            break
        sure += counts[b]
    if last is None:
        return df
    rest = Window.partitionBy("_bin").orderBy(*order)  # one bin in one task, not k rows of every task at the driver
    cut = binned.where(F.col("_bin") == last).withColumn("_at", F.row_number().over(rest)).where(F.col("_at") <= k - sure).drop("_at")
    return binned.where(F.col("_bin") > last).unionByName(cut).drop("_bin")


def _top(df: DataFrame, order: list[Column], k: int, magnitude: Column) -> DataFrame:
    """The first k rows in an order that ``magnitude`` descending leads."""
    return _first(df, order, k, magnitude_bin(magnitude))


def drawn_first(df: DataFrame, k: int, seed: int, step: int) -> DataFrame:
    """The k coordinates that the shared random order puts first."""
    drawn = fill_order(F.col("coord"), seed, step)
    return _first(df, [drawn, F.col("coord")], k, -F.floor(drawn / (PRIME // FILL_BINS + 1)).cast("int"))


def top_estimate(est: DataFrame, k: int) -> DataFrame:
    """SUPPORT (coord, est, heavy) of the k largest |est|; ties to the smaller coordinate."""
    size = F.abs("est")
    return _top(est.select("coord", "est"), [size.desc(), F.col("coord")], k, size).withColumn("heavy", F.lit(True))


def heavy_only(split: DataFrame, k: int) -> DataFrame:
    """The heavy coordinates, the k largest if there are more."""
    size = F.abs("est")
    return _top(split.where("heavy"), [size.desc(), F.col("coord")], k, size)


def random_fill(split: DataFrame, count: int, seed: int, step: int) -> DataFrame:
    """``count`` light coordinates in the shared random order."""
    return drawn_first(split.where(~F.col("heavy")), count, seed, step)


def heavy_random(split: DataFrame, k: int, seed: int, step: int) -> DataFrame:
    """Heavy coordinates, filled with random light ones to k.

    For a small k one ordering does cap and fill; for a large one the heavy
    ones are counted, and cap and fill each find their own threshold.
    """
    if k < 1:
        raise ValueError("k must be positive")
    size = F.when(F.col("heavy"), F.abs("est"))
    drawn = F.when(~F.col("heavy"), fill_order(F.col("coord"), seed, step))
    if k <= THRESHOLD_K:
        return split.orderBy(F.col("heavy").desc(), size.desc(), drawn, F.col("coord")).limit(k)
    heavy = split.where("heavy").count()
    return heavy_only(split, k) if heavy >= k else split.where("heavy").unionByName(random_fill(split, k - heavy, seed, step))


def exact_values(coords: DataFrame, support: DataFrame) -> DataFrame:
    """SUPPORT with ``exact``, the sum over workers of the true values; 0 where no worker has the coordinate.

    The support, at most k rows, is broadcast if Spark's size check allows.
    """
    columns = support.columns
    zero = F.lit(0).cast(dict(coords.dtypes)["val"]).alias("val")
    hit = coords.select("coord", "val").join(support, "coord").select(*columns, "val")
    return hit.unionByName(support.select(*columns, zero)).groupBy(*columns).agg(F.sum("val").alias("exact"))


def recover(merged: DataFrame, spec: SketchSpec, candidates: DataFrame, k: int, *, method: str = "heavy_random", seed: int = 1, step: int = 1, literal_signed: bool = False) -> DataFrame:
    """SUPPORT of a merged sketch by ``heavy_random``, ``top_estimate`` or ``heavy_only``."""
    small = spec.size <= sk.MAX_BLOCK_CELLS
    if method == "top_estimate":
        return top_estimate(sk.estimate_blocks(merged, spec, candidates) if small else sk.estimate(merged, spec, candidates), k)
    if small:
        split = _split(sk.estimate_with_norm(merged, spec, candidates), k, literal_signed)
    else:
        split = split_heavy(sk.estimate(merged, spec, candidates), sk.l2_squared(merged, spec), k, literal_signed=literal_signed)
    if method == "heavy_only":
        return heavy_only(split, k)
    if method == "heavy_random":
        return heavy_random(split, k, seed, step)
    raise ValueError(f"unknown recovery {method}")
