"""Searches of some vectors against all, shard by shard."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Vectors in a shard at most, on average (some 100 MB with 64 components), and at least while there are idle cores.
SHARD_VECTORS = 200_000
LEAST_VECTORS = 16_384
#: Searches that are answered together.
BLOCK = 512


def usable(df: DataFrame, column: str = "embedding") -> DataFrame:
    """Rows whose vector is not null, not empty, not zero and wholly finite."""
    odd = lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf"))
    return df.where(F.col(column).isNotNull() & (F.size(column) > 0) & ~F.exists(column, odd) & F.exists(column, lambda v: v != 0))


def unit_vectors(vectors: np.ndarray) -> np.ndarray:
    """Rows divided by their length, in double precision, whatever their scale."""
    x = np.asarray(vectors, np.float64)
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def shards_for(n: int, cores: int) -> int:
    """As few shards as hold ``n`` vectors; some more where that leaves cores idle, for every query visits every shard."""
    return max(1, -(-n // SHARD_VECTORS), min(cores, -(-n // LEAST_VECTORS)))


def search_shards(members: DataFrame, queries: DataFrame, build: Callable, answer: Callable, schema: str, *, shards: int | None = None) -> DataFrame:
    """Every row of ``queries(id, v array<double>)`` against every shard of ``members(id, v, weight)``.

    A shard's task calls ``build(rows, ids, weights)`` once and then
    ``answer(index, rows, ids)`` for each block of queries; it holds its own
    vectors and one block at a time. Vectors of different lengths do not meet.
    The number of shards grows with the members so that a shard fits a task; a
    query is sent to each, so with one shard nothing is copied.
    """
    shards = shards or shards_for(members.count(), members.sparkSession.sparkContext.defaultParallelism)
    own = members.select(F.size("v").alias("dim"), F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int").alias("shard"), F.lit(0).alias("is_query"), "id", "v", F.col("weight").cast("long").alias("weight"))
    asked = queries.select(F.size("v").alias("dim"), F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("shard"), F.lit(1).alias("is_query"), "id", "v", F.lit(0).cast("long").alias("weight"))
    order = ["shard", "dim", "is_query", "id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, held, index, ready = None, [], None, False
        for batch in batches:
            dims, parts, kinds, ids, weights = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1, 2, 3, 5))
            new = (np.diff(dims, prepend=-1) != 0) | (np.diff(parts, prepend=-1) != 0) | (np.diff(kinds, prepend=-1) != 0)
            starts = np.flatnonzero(new)
            for start, stop in zip(starts, np.append(starts[1:], len(ids))):
                key = (dims[start], parts[start])
                rows = batch.column(4).slice(start, stop - start).flatten().to_numpy(zero_copy_only=False).reshape(stop - start, dims[start])
                if key != at:
                    at, held, index, ready = key, [], None, False
                if kinds[start] == 0:
                    held.append((rows, ids[start:stop], weights[start:stop]))
                    continue
                if not ready:
                    ready = True
                    index = build(*(np.concatenate(c) for c in zip(*held))) if held else None
                    held = []
                if index is not None:
                    for k in range(0, len(rows), BLOCK):
                        yield answer(index, rows[k : k + BLOCK], ids[start + k : min(start + k + BLOCK, stop)])

    dealt = own.unionByName(asked).select("dim", "shard", "is_query", "id", "v", "weight").repartitionById(shards, F.col("shard"))
    return dealt.sortWithinPartitions(*order).mapInArrow(run, schema)
