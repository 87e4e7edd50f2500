"""Nearest neighbours by a hash-prefix forest over sorted arrays.

Each tree hashes a vector to a long string of bits, one for a random
hyperplane each, and keeps the strings sorted; a node of the tree is a range of
that array with a common prefix. A query descends in each tree to the longest
prefix that it shares with anything, then ascends in all trees at once, a bit
at a time, until the ranges hold enough candidates. Candidates are ranked by
their exact inner product.

Largest inner products become nearest directions by one more component,
sqrt(M^2 - |x|^2), where M is the greatest length.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treesketch.llm.sharding import search_shards, usable
from treesketch.llm.storage import only
from treesketch.llm.wordhash import mix64

TREES = 12
BITS = 48
#: Candidates, in multiples of k over all trees, that the ascent asks for at first.
FIRST_CANDIDATES = 20
#: Queries of each block that are audited by brute force, and the recall that they must reach.
AUDITED = 16
AUDIT_RECALL = 0.95


def _normals(rows: int, columns: int, seed: int) -> np.ndarray:
    """Standard normal numbers that depend on the seed alone."""
    u = (mix64(np.arange(2 * rows * columns, dtype=np.uint64) + np.uint64(seed << 32)) >> np.uint64(11)).astype(np.float64) / 2.0**53
    u = u.reshape(2, rows, columns)
    return np.sqrt(-2 * np.log(np.maximum(u[0], 1e-300))) * np.cos(2 * np.pi * u[1])


class PrefixForest:
    def __init__(self, vectors: np.ndarray, longest: float, trees: int = TREES, bits: int = BITS, seed: int = 9):
        self.x = np.ascontiguousarray(vectors, np.float64)
        self.trees, self.bits = trees, bits
        self._size = float(np.abs(self.x).max(initial=0.0)) * self.x.shape[1]
        scaled = self.x / longest
        rest = np.sqrt(np.maximum(0.0, 1.0 - (scaled * scaled).sum(1)))
        self._planes = _normals(trees * bits, self.x.shape[1] + 1, seed)
        strings = self._strings(np.column_stack([scaled, rest]))
        self.order = np.argsort(strings, axis=1, kind="stable").astype(np.int32)
        self.sorted = np.take_along_axis(strings, self.order, 1)

    def _strings(self, points: np.ndarray) -> np.ndarray:
        signs = (points @ self._planes.T > 0).reshape(len(points), self.trees, self.bits)
        return (signs.astype(np.uint64) << np.arange(self.bits - 1, -1, -1, dtype=np.uint64)).sum(2, dtype=np.uint64).T.copy()

    def query_strings(self, queries: np.ndarray) -> np.ndarray:
        scale = np.abs(queries).max(1, keepdims=True)
        return self._strings(np.column_stack([queries / scale, np.zeros(len(queries))]))

    def _longest(self, strings: np.ndarray) -> np.ndarray:
        """Descent: the length of the longest prefix that each query shares with an entry of each tree."""
        out = np.zeros(strings.shape, np.int64)
        for t in range(self.trees):
            at = np.searchsorted(self.sorted[t], strings[t])
            for near in (np.maximum(at - 1, 0), np.minimum(at, len(self.x) - 1)):  # the best match is a neighbour in the order
                apart = self.sorted[t][near] ^ strings[t]
                out[t] = np.maximum(out[t], self.bits - np.frexp(apart.astype(np.float64))[1])  # fewer than 53 bits are exact
        return out

    def candidates(self, strings: np.ndarray, wanted: int) -> list[np.ndarray]:
        """For each query the distinct positions under its prefixes of one length, the longest with ``wanted`` entries over all trees.

        A query descends to its longest match in each tree; the ascent starts
        at the longest of all, and a tree joins when the common length has come
        down to its own match.
        """
        n_queries = strings.shape[1]
        low, high = np.zeros((self.trees, n_queries), np.int64), np.full((self.trees, n_queries), len(self.x))
        deepest = self._longest(strings).max(0)
        todo = np.arange(n_queries)
        for length in range(int(deepest.max(initial=0)), -1, -1):
            here = todo[deepest[todo] >= length]
            if not len(here):
                continue
            cut = np.uint64(self.bits - length)
            first = strings[:, here] >> cut << cut
            last = first + (np.uint64(1) << cut)
            a = np.stack([np.searchsorted(self.sorted[t], first[t]) for t in range(self.trees)])
            b = np.stack([np.searchsorted(self.sorted[t], last[t]) for t in range(self.trees)])
            enough = (b - a).sum(0) >= wanted
            low[:, here[enough]], high[:, here[enough]] = a[:, enough], b[:, enough]
            todo = np.setdiff1d(todo, here[enough])
            if not len(todo):
                break
        return [np.unique(np.concatenate([self.order[t, low[t, i] : high[t, i]] for t in range(self.trees)])) for i in range(n_queries)]

    def nearest(self, queries: np.ndarray, k: int, wanted: int) -> list[tuple[np.ndarray, np.ndarray]]:
        """Positions and inner products of each query's k best candidates; ties to the earlier position.

        A matrix product ranks the candidates but for its last bits, which
        depend on a row's place; those that can be among the k best are scored
        again, each by a sum of one fixed order, so that equal vectors tie.
        """
        out = []
        for q, found in zip(queries, self.candidates(self.query_strings(queries), wanted)):
            rough = self.x[found] @ q
            if len(found) > k:
                slack = 1e-9 * float(np.abs(q).max()) * self._size
                least = np.partition(rough, len(rough) - k)[len(rough) - k]
                found = found[rough >= least - slack]
            scores = (self.x[found] * q).sum(1)
            best = np.lexsort((found, -scores))[:k]
            out.append((found[best], scores[best]))
        return out


class _Shard:
    def __init__(self, rows: np.ndarray, ids: np.ndarray, longest: float, wanted: int):
        order = np.argsort(ids, kind="stable")  # so that earlier positions are smaller ids
        self.ids, self.forest, self.wanted = ids[order], PrefixForest(rows[order], longest), wanted


def nearest_neighbours(vectors: DataFrame, queries: DataFrame, *, k: int = 20, shards: int | None = None) -> DataFrame:
    """``query_id, rank, vec_id, score``: the k largest inner products found for each row of ``queries``.

    Both tables have ``vec_id, embedding``. Vectors that are null, empty, zero
    or hold null or non-finite components, and rows without vec_id, take no
    part; a row with the query's own vec_id is not its neighbour; repeated rows
    count once. Every shard audits each block of queries and ascends further
    until the audit's recall is reached, down to all its rows.
    """
    shape = [F.col("vec_id").cast("long").alias("id"), F.col("embedding").cast("array<double>").alias("v")]
    members = usable(only(vectors, "vec_id", "embedding").select(*shape), "v").where(F.col("id").isNotNull()).distinct()
    asked = usable(only(queries, "vec_id", "embedding").select(*shape), "v").where(F.col("id").isNotNull()).distinct()
    square = F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x)
    longest = float(members.agg(F.sqrt(F.max(square)).alias("m")).first()["m"] or 1.0)

    def answer(shard: _Shard, rows: np.ndarray, ids: np.ndarray) -> pa.RecordBatch:
        forest, deep = shard.forest, k + 1
        sample = np.linspace(0, len(rows) - 1, min(AUDITED, len(rows))).astype(np.int64)
        truth = [set(np.argsort(-(forest.x @ rows[i]), kind="stable")[:k].tolist()) for i in sample]
        while True:
            hits = sum(len(truth[j].intersection(found.tolist())) for j, (found, _) in enumerate(forest.nearest(rows[sample], k, shard.wanted)))
            if hits >= AUDIT_RECALL * sum(map(len, truth)) or shard.wanted >= forest.trees * len(forest.x):
                break
            shard.wanted = shard.wanted * 3 // 2
        found = forest.nearest(rows, deep, shard.wanted)
        query = np.repeat(ids, [len(f) for f, _ in found])
        near, score = shard.ids[np.concatenate([f for f, _ in found])], np.concatenate([s for _, s in found])
        keep = query != near
        return pa.RecordBatch.from_arrays([pa.array(query[keep]), pa.array(near[keep]), pa.array(score[keep])], names=["query_id", "vec_id", "score"])

    found = search_shards(members.withColumn("weight", F.lit(1)), asked, lambda rows, ids, _: _Shard(rows, ids, longest, FIRST_CANDIDATES * k), answer, "query_id long, vec_id long, score double", shards=shards)
    best = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), F.col("vec_id"))
    return best.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
