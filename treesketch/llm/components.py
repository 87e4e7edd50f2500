"""Connected components by alternating large-star and small-star steps."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treesketch.llm.storage import materialize

#: Edges of a task that are joined to a forest at a time.
FOREST_EDGES = 1 << 20


def star_forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each vertex of the edges (a[i], b[i]) with the least vertex of its component, but for that one itself."""
    names, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    u, v = at[: len(a)], at[len(a) :]
    parent = np.arange(len(names))
    while True:
        x, y = parent[u], parent[v]
        apart = x != y
        if not apart.any():
            break
        np.minimum.at(parent, np.maximum(x, y)[apart], np.minimum(x, y)[apart])  # of a root's neighbours the least becomes its parent
        while True:
            above = parent[parent]
            if np.array_equal(above, parent):
                break
            parent = above
    moved = np.flatnonzero(parent != np.arange(len(names)))
    return names[moved], names[parent[moved]]


def _forests(edges: DataFrame) -> DataFrame:
    """Fewer edges with the same components: a task's edges become stars before anything is shuffled."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []

        def made() -> pa.RecordBatch:
            a, b = star_forest(*(np.concatenate(c) for c in zip(*held)))
            held.clear()
            return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

        for batch in batches:
            if batch.num_rows:
                held.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
            if sum(len(x) for x, _ in held) >= FOREST_EDGES:
                yield made()
        if held:
            yield made()

    return edges.select("a", "b").mapInArrow(run, "a long, b long")


def _large_star(edges: DataFrame) -> DataFrame:
    """Each vertex links its larger neighbours to the least of its neighbourhood."""
    sides = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = sides.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
    return sides.where(F.col("b") > F.col("a")).join(least.hint("merge"), "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where(F.col("a") != F.col("b"))


def _small_star(edges: DataFrame) -> DataFrame:
    """Each vertex links itself and its smaller neighbours to the least of these."""
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("m"))
    moved = down.join(least.hint("merge"), "a").select(F.inline(F.array(F.struct(F.col("b").alias("a"), F.col("m").alias("b")), F.struct(F.col("a"), F.col("m").alias("b")))))
    return moved.where(F.col("a") != F.col("b")).distinct()


def connected_components(edges: DataFrame, *, max_rounds: int = 64) -> DataFrame:
    """``vertex, component`` for each end of ``edges(a, b)``; component is the least vertex reachable.

    ``edges`` should be a written table; so is what each round makes. Tasks
    join their own edges to stars first, so the rounds handle about as many
    rows as there are vertices. They end when every component is a star around
    its least vertex, which a fingerprint of the edges shows; their number
    grows with the logarithm of the longest path.
    Self-links and repeated links are allowed; no links give no rows.
    """
    loops = edges.where(F.col("a") == F.col("b")).select(F.col("a").alias("vertex"), F.col("a").alias("component"))
    now = materialize(_forests(edges.where(F.col("a") != F.col("b"))).distinct(), "edges")
    mark = F.struct(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")))
    before = now.agg(mark.alias("m")).first()["m"]
    for _ in range(max_rounds):
        if not before[0]:
            break
        now = materialize(_small_star(_large_star(now)), "edges")
        after = now.agg(mark.alias("m")).first()["m"]
        if after == before:
            break
        before = after
    else:
        raise RuntimeError(f"no fixed point after {max_rounds} rounds")
    ends = now.select(F.inline(F.array(F.struct(F.col("a").alias("vertex"), F.col("b").alias("component")), F.struct(F.col("b").alias("vertex"), F.col("b").alias("component")))))
    return ends.unionByName(loops).groupBy("vertex").agg(F.min("component").alias("component"))
