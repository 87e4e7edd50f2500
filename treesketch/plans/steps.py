"""One whole exchange of each method on a table of worker vectors."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treesketch.functions.hashing import SketchSpec
from treesketch.operators import compressors, recovery, topology
from treesketch.operators import sketch as sk
from treesketch.sources import scratch


def sketch_step(coords: DataFrame, spec: SketchSpec, *, d: int, k: int, workers: int, topology_kind: str = "tree", recover: str = "heavy_random", seed: int = 1, step: int = 1, exact: bool = True, literal_signed: bool = False, candidates: DataFrame | None = None) -> DataFrame:
    """(coord, est, heavy, exact): compress, merge along a tree or at a star, recover the support, fetch exact values.

    ``candidates`` limits the point queries to some coordinates (those seen
    anywhere, say), for dimensions too large to enumerate. ``exact=False``
    leaves the second exchange out and takes the estimates. The vector and the
    support, which both exchanges read, are written to the shared folder once.
    """
    if exact:
        coords, _ = scratch.keep(coords, "vector")
    cells = sk.build(coords, spec)
    merged = topology.tree_merge(cells, workers) if topology_kind == "tree" else topology.star_merge(cells)
    asked = candidates if candidates is not None else sk.dimension(coords.sparkSession, d)
    support = recovery.recover(merged, spec, asked, k, method=recover, seed=seed, step=step, literal_signed=literal_signed)
    return recovery.exact_values(coords, scratch.keep(support, "support")[0]) if exact else support.withColumn("exact", F.col("est"))


def residual(coords: DataFrame, support: DataFrame) -> DataFrame:
    """What each worker still owes after a step: its vector without the coordinates whose exact values were sent."""
    return coords.join(support.select("coord"), "coord", "left_anti").select("worker", "coord", "val")


def apply_update(weights: DataFrame, update: DataFrame, rate: float, *, workers: int = 1, combine: str = "mean") -> DataFrame:
    """WEIGHT(coord, w) less rate * update on the update's coordinates only; absent weights are 0."""
    if combine not in ("mean", "sum"):
        raise ValueError("combine is 'mean' or 'sum'")
    factor = rate / (workers if combine == "mean" else 1)
    both = weights.join(update.select("coord", F.col("exact").alias("g")), "coord", "outer")
    return both.select("coord", (F.coalesce("w", F.lit(0.0)) - F.lit(factor) * F.coalesce("g", F.lit(0))).alias("w"))


def method_step(coords: DataFrame, method: str, spec: SketchSpec, *, d: int, k: int, workers: int, **options) -> DataFrame:
    """(coord, exact): what each method hands to the update."""
    if method == "tree_sketch":
        return sketch_step(coords, spec, d=d, k=k, workers=workers, **options).select("coord", "exact")
    if method == "star_sketch":
        return sketch_step(coords, spec, d=d, k=k, workers=workers, topology_kind="star", **options).select("coord", "exact")
    named = {"dense": lambda: compressors.dense_sum(coords), "star_topk": lambda: compressors.star_topk(coords, k), "tree_topk": lambda: compressors.tree_topk(coords, k, workers)}
    return named[method]().select("coord", F.col("val").alias("exact"))
