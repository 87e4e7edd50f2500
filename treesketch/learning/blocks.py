"""Training examples as NumPy blocks, one row for some examples of a worker."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treesketch.functions.hashing import PRIME, np_fill_order
from treesketch.learning.schedule import worker_of
from treesketch.sources import tables

#: Examples in a block; a mini-batch takes its share of each block of the worker.
BLOCK_EXAMPLES = 4096
#: Languages of the documents, by class (fixed values).
LANGUAGES = ("en", "fr", "de", "es")
#: Every so many-th key is held out.
HOLDOUT = 5

BLOCK_SCHEMA = "worker int, held_out boolean, n int, keys binary, labels binary, index binary, value binary, starts binary"


def _pack(rows: DataFrame, *, unit: bool = False) -> DataFrame:
    """Blocks of ``rows(worker, held_out, key, label, index array, value array)``, packed where the rows are, by key in a part of an Arrow batch.

    ``unit`` scales each example to unit length: here and not in SQL, where a
    length within the transform would be computed again for each word.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            worker, out = batch.column(0).fill_null(-1).to_numpy(), batch.column(1).to_numpy(zero_copy_only=False)
            cuts = [0, *(np.flatnonzero((worker[1:] != worker[:-1]) | (out[1:] != out[:-1])) + 1).tolist(), len(worker)]
            for low, high in zip(cuts, cuts[1:]):
                for at in range(low, high, BLOCK_EXAMPLES):
                    part = batch.slice(at, min(BLOCK_EXAMPLES, high - at))
                    starts = np.concatenate([[0], np.cumsum(part.column(4).value_lengths().to_numpy())])
                    flat = [(part.column(2), np.int64), (part.column(3), np.int64), (part.column(4).flatten(), np.int64), (part.column(5).flatten(), np.float64)]
                    arrays = [*(c.to_numpy(zero_copy_only=False).astype(t) for c, t in flat), starts.astype(np.int64)]
                    if unit:
                        row = np.repeat(np.arange(part.num_rows), np.diff(starts))
                        arrays[3] = arrays[3] / np.sqrt(np.bincount(row, arrays[3] * arrays[3], part.num_rows))[row]
                    yield pa.RecordBatch.from_arrays([part.column(0).slice(0, 1), part.column(1).slice(0, 1), pa.array([part.num_rows], pa.int32()), *[pa.array([a.tobytes()], pa.binary()) for a in arrays]], names=["worker", "held_out", "n", "keys", "labels", "index", "value", "starts"])

    return rows.select("worker", "held_out", "key", "label", "index", "value").sortWithinPartitions("worker", "held_out", "key").mapInArrow(run, BLOCK_SCHEMA)


def dealt(keys: np.ndarray, worker: int | None, workers: int) -> np.ndarray:
    """The worker of each example of a block: the block's own, or without one that of the key, as ``worker_of`` has it."""
    return np_fill_order(keys % PRIME, 0, 0) % workers if worker is None else np.full(len(keys), worker)


def embedding_blocks(spark: SparkSession, sf_dir: str, workers: int, *, planted: bool = True) -> DataFrame:
    """The small problem: 64 components, ten classes; the planted label, or the given one as a negative control."""
    rows = tables.read_table(spark, sf_dir, "embeddings").where(F.col("embedding").isNotNull())
    if planted:
        rows = rows.drop("label").join(tables.planted_labels(spark, sf_dir).withColumnRenamed("key", "vec_id"), "vec_id")
    key = F.col("vec_id")
    index = F.sequence(F.lit(0), F.size("embedding") - 1).cast("array<long>")
    return _pack(rows.where(F.col("label").isNotNull()).select(worker_of(key, workers).alias("worker"), (key % HOLDOUT == 0).alias("held_out"), key.alias("key"), F.col("label").cast("long").alias("label"), index.alias("index"), F.col("embedding").cast("array<double>").alias("value")))


def language_blocks(spark: SparkSession, sf_dir: str, workers: int, *, buckets: int = 4096) -> DataFrame:
    """The large sparse problem: hashed words, log counts of unit length, and the language as label. With 0 ``workers`` the blocks have none, see ``dealt``."""
    docs = tables.read_table(spark, sf_dir, "documents")
    label = F.array_position(F.array(*[F.lit(x) for x in LANGUAGES]), F.col("lang")) - 1
    rows = docs.where(F.col("lang").isin(*LANGUAGES) & F.col("text").isNotNull()).select(F.col("doc_id").alias("key"), label.alias("label"), F.explode(tables.words(F.col("text"))).alias("word"))
    counted = rows.where(F.col("word") != "").groupBy("key", "label", tables.word_coordinate(F.col("word"), buckets).alias("j")).agg(F.log1p(F.count(F.lit(1)).cast("double")).alias("x"))
    bags = counted.groupBy("key", "label").agg(F.array_sort(F.collect_list(F.struct("j", "x"))).alias("f"))
    key = F.col("key")
    worker = worker_of(key, workers) if workers else F.lit(None).cast("int")
    return _pack(bags.select(worker.alias("worker"), (key % HOLDOUT == 0).alias("held_out"), "key", "label", F.col("f.j").alias("index"), F.col("f.x").alias("value")), unit=True)


#: Features from which on examples are not made dense.
SPARSE_FEATURES = 256


class SparseRows:
    """Examples as the matrix x of a model's products ``x @ m`` and ``m @ x``, by what they have other than zeros."""

    __array_ufunc__ = None

    def __init__(self, block: Block, features: int):
        self.shape = (block.n, features)
        self.row, self.index, self.value = np.repeat(np.arange(block.n), np.diff(block.starts)), block.index, block.value

    def __matmul__(self, m: np.ndarray) -> np.ndarray:
        if m.ndim == 1:
            return (self @ m[:, None])[:, 0]
        return np.stack([np.bincount(self.row, self.value * m[self.index, c], self.shape[0]) for c in range(m.shape[1])], 1)

    def __rmatmul__(self, m: np.ndarray) -> np.ndarray:
        if m.ndim == 1:
            return (m[None] @ self)[0]
        return np.stack([np.bincount(self.index, self.value * r[self.row], self.shape[1]) for r in m])


class Block:
    """One row of blocks as arrays."""

    def __init__(self, row: dict):
        self.n = row["n"]
        self.keys, self.labels, self.index, self.starts = (np.frombuffer(row[c], np.int64) for c in ("keys", "labels", "index", "starts"))
        self.value = np.frombuffer(row["value"])

    def dense(self, take: np.ndarray, features: int) -> np.ndarray:
        x = np.zeros((len(take), features))
        for i, k in enumerate(take):
            at = slice(self.starts[k], self.starts[k + 1])
            x[i, self.index[at]] = self.value[at]
        return x

    def rows(self, features: int) -> np.ndarray | SparseRows:
        """All examples for a model: memory goes with what they have, not with examples * features."""
        return SparseRows(self, features) if features >= SPARSE_FEATURES else self.dense(np.arange(self.n), features)

    def some(self, take: np.ndarray) -> dict:
        """A row of the chosen examples only."""
        sizes = self.starts[take + 1] - self.starts[take]
        starts = np.concatenate([[0], np.cumsum(sizes)])
        at = np.repeat(self.starts[take] - starts[:-1], sizes) + np.arange(starts[-1])
        parts = {"keys": self.keys[take], "labels": self.labels[take], "index": self.index[at], "value": self.value[at], "starts": starts.astype(np.int64)}
        return {"n": len(take)} | {c: x.tobytes() for c, x in parts.items()}


def joined(rows: list[dict]) -> dict:
    """Rows of blocks as one."""
    if len(rows) == 1:
        return rows[0]
    starts, shift = [np.zeros(1, np.int64)], 0
    for row in rows:
        starts.append(np.frombuffer(row["starts"], np.int64)[1:] + shift)
        shift = int(starts[-1][-1]) if len(starts[-1]) else shift
    return {"n": sum(r["n"] for r in rows), "starts": np.concatenate(starts).tobytes()} | {c: b"".join(r[c] for r in rows) for c in ("keys", "labels", "index", "value")}
