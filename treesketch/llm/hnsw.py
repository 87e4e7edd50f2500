"""Embedding near-duplicates: navigable small-world graphs, one for each shard.

A graph is built and searched for many vectors at a time: beams move in
lockstep, each step a gather and a product of small matrices. Every vector is
searched in every shard; beams widen while links still reach their ends, and
for each block of searches an audit by brute force decides whether all of its
beams are wide enough.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treesketch.llm.components import connected_components
from treesketch.llm.sharding import BLOCK, search_shards, unit_vectors, usable
from treesketch.llm.storage import materialize, only
from treesketch.llm.wordhash import mix64

#: Neighbours kept above the lowest layer; the lowest keeps twice as many.
DEGREE = 12
BUILD_BEAM = 40
SEARCH_BEAM = 24
#: A beam that times this many reaches the shard's size is answered by a scan of the shard; vectors that a step of a search gathers at most.
SCAN = 8
GATHERED = 1 << 18
#: Members that set a shard's beam before it answers, and searches of each block that are audited.
TUNED = 1024
AUDITED = 16
#: The share of true links that an audit asks for.
AUDIT_RECALL = 0.99


class SmallWorld:
    """Hierarchical navigable small-world graph over unit vectors, by inner product."""

    def __init__(self, vectors: np.ndarray, degree: int = DEGREE, build_beam: int = BUILD_BEAM, seed: int = 3):
        self.x = np.ascontiguousarray(vectors, np.float32)
        n = len(self.x)
        draw = (mix64(np.arange(n, dtype=np.uint64) + np.uint64(seed << 20)) >> np.uint64(11)).astype(np.float64) / 2.0**53
        self.level = np.minimum((-np.log(np.maximum(draw, 1e-300)) / np.log(degree)).astype(np.int64), 6)
        if n:
            self.level[0] = max(1, int(self.level.max()))
        self.neighbours = [np.full((n, degree * (1 if k else 2)), -1, np.int32) for k in range(int(self.level.max(initial=0)) + 1)]
        done, beam = 1, build_beam
        while done < n:
            stop = min(n, done + max(1, min(done // 2, BLOCK)))
            self._insert(np.arange(done, stop), beam)
            done = stop

    def _insert(self, new: np.ndarray, beam: int) -> None:
        q = self.x[new]
        entry = np.zeros((len(new), 1), np.int64)
        for layer in range(len(self.neighbours) - 1, -1, -1):
            here = self.level[new] >= layer
            ids, sims = self._beam(q, entry, beam if here.any() else 1, layer)
            if here.any():
                batch = new[here]
                among = q[here] @ q[here].T
                np.fill_diagonal(among, -np.inf)
                width = min(beam, len(batch))
                near = np.argpartition(-among, width - 1, axis=1)[:, :width]
                cand = np.concatenate([ids[here], batch[near]], axis=1)
                cand_sims = np.concatenate([sims[here], np.take_along_axis(among, near, 1)], axis=1)
                cand[~np.isfinite(cand_sims)] = -1
                self._link(batch, cand, cand_sims, layer)
            entry = ids[:, :1]

    def _select(self, cand: np.ndarray, sims: np.ndarray, keep: int) -> np.ndarray:
        """Of each row's candidates, those nearer to the row's vector than to any one taken before."""
        order = np.argsort(-sims, axis=1, kind="stable")[:, : 3 * keep]
        cand, sims = np.take_along_axis(cand, order, 1), np.take_along_axis(sims, order, 1)
        rows, width = cand.shape
        vectors = self.x[np.maximum(cand, 0)]
        between = np.matmul(vectors, vectors.transpose(0, 2, 1))
        taken, count = np.zeros((rows, width), bool), np.zeros(rows, np.int64)
        for j in range(width):
            blocked = (taken & (between[:, j] > sims[:, j, None])).any(1)
            ok = (cand[:, j] >= 0) & ~blocked & (count < keep)
            taken[:, j] = ok
            count += ok
        for j in range(width):  # room that is left goes to the nearest of the others
            ok = (cand[:, j] >= 0) & ~taken[:, j] & (count < keep)
            taken[:, j] |= ok
            count += ok
        first = np.argsort(~taken, axis=1, kind="stable")[:, :keep]
        out = np.where(np.take_along_axis(taken, first, 1), np.take_along_axis(cand, first, 1), -1)
        return np.pad(out, ((0, 0), (0, keep - out.shape[1])), constant_values=-1)

    def _link(self, batch: np.ndarray, cand: np.ndarray, sims: np.ndarray, layer: int) -> None:
        table = self.neighbours[layer]
        keep = table.shape[1]
        chosen = self._select(cand, np.where(cand >= 0, sims, -np.inf), keep)
        table[batch] = chosen
        back, to = np.repeat(batch, keep), chosen.ravel()
        back, to = back[to >= 0], to[to >= 0]
        if not len(to):
            return
        strength = np.einsum("ij,ij->i", self.x[back], self.x[to])
        order = np.lexsort((-strength, to))
        back, to = back[order], to[order]
        at = np.flatnonzero(np.diff(to, prepend=-1))
        place = np.arange(len(to)) - np.repeat(at, np.diff(np.append(at, len(to))))
        owners = to[at]
        width = min(2 * keep, int(place.max()) + 1)
        added = np.full((len(owners), width), -1, np.int64)
        row = np.repeat(np.arange(len(owners)), np.diff(np.append(at, len(to))))
        fits = place < width
        added[row[fits], place[fits]] = back[fits]
        both = np.concatenate([table[owners].astype(np.int64), added], axis=1)
        both.sort(axis=1)
        both[:, 1:][both[:, 1:] == both[:, :-1]] = -1
        sims = np.einsum("ijk,ik->ij", self.x[np.maximum(both, 0)], self.x[owners])
        table[owners] = self._select(both, np.where(both >= 0, sims, -np.inf), keep)

    def _beam(self, q: np.ndarray, entry: np.ndarray, width: int, layer: int) -> tuple[np.ndarray, np.ndarray]:
        """The best ``width`` found for each row of ``q``, best first; -1 with -inf where there are fewer. A wide beam opens many of its entries at a time."""
        at_once = max(3, width // 8)
        table, n = self.neighbours[layer], len(self.x)
        rows = len(q)
        seen = np.zeros((rows, n + 1), bool)
        seen[:, n] = True
        ids = np.full((rows, width), n, np.int64)
        sims = np.full((rows, width), -np.inf, np.float32)
        k = min(width, entry.shape[1])
        ids[:, :k] = np.where(entry[:, :k] >= 0, entry[:, :k], n)
        sims[:, :k] = np.where(ids[:, :k] < n, np.einsum("ijk,ik->ij", self.x[np.minimum(ids[:, :k], n - 1)], q), -np.inf)
        np.put_along_axis(seen, ids[:, :k], True, 1)
        open_ = np.isfinite(sims)
        active = np.arange(rows)
        at_once = min(at_once, width)
        while True:
            active = active[open_[active].any(1)]
            if not len(active):
                break
            turn = np.argsort(~open_[active], axis=1, kind="stable")[:, :at_once]
            go = np.take_along_axis(open_[active], turn, 1)
            mine = open_[active]
            np.put_along_axis(mine, turn, False, 1)
            heads = np.where(go, np.take_along_axis(ids[active], turn, 1), 0)
            near = np.where(go[:, :, None], table[heads], -1).reshape(len(active), -1).astype(np.int64)
            near[near < 0] = n
            near.sort(axis=1)
            near[:, 1:][near[:, 1:] == near[:, :-1]] = n
            fresh = ~seen[active[:, None], near]
            seen[active[:, None], near] = True
            found = np.where(fresh, np.einsum("ijk,ik->ij", self.x[np.minimum(near, n - 1)], q[active]), -np.inf).astype(np.float32)
            all_ids = np.concatenate([ids[active], near], axis=1)
            all_sims = np.concatenate([sims[active], found], axis=1)
            all_open = np.concatenate([mine, np.isfinite(found)], axis=1)
            best = np.argsort(-all_sims, axis=1, kind="stable")[:, :width]
            ids[active], sims[active] = np.take_along_axis(all_ids, best, 1), np.take_along_axis(all_sims, best, 1)
            open_[active] = np.take_along_axis(all_open, best, 1) & np.isfinite(sims[active])
        return np.where(np.isfinite(sims), ids, -1), sims

    def search(self, q: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
        q = np.asarray(q, np.float32)
        entry = np.zeros((len(q), 1), np.int64)
        for layer in range(len(self.neighbours) - 1, 0, -1):
            entry = self._beam(q, entry, 4, layer)[0]
        return self._beam(q, entry, width, 0)

    def within(self, q: np.ndarray, least: float, width: int) -> list[np.ndarray]:
        """For each row of ``q`` the found positions with similarity ``least`` at least; beams that are full of them are widened."""
        n = len(self.x)
        out: list[np.ndarray] = [np.zeros(0, np.int64)] * len(q)
        todo = np.arange(len(q))
        while len(todo):
            full = np.zeros(len(todo), bool)
            wide = SCAN * width >= n
            rows = BLOCK if wide else max(1, GATHERED // (max(3, width // 8) * self.neighbours[0].shape[1]))
            for at in range(0, len(todo), rows):
                part = todo[at : at + rows]
                if wide:  # a beam of a good part of the graph is dearer than all of it
                    for i, sims in zip(part, q[part].astype(np.float32) @ self.x.T):
                        out[i] = np.flatnonzero(sims >= least)
                    continue
                ids, sims = self.search(q[part], width)
                near = sims >= least
                full[at : at + rows] = near.sum(1) > 0.75 * width
                for i, row, hit in zip(part, ids, near):
                    out[i] = row[hit]
            todo, width = todo[full], 4 * width
        return out


#: Similarity that single precision may lack; found neighbours are checked in double precision.
SLACK = 1e-4


class _Shard:
    """A shard's graph, the beam that its audits asked for so far, and the components that its answers have joined.

    Before any answer the beam is set by brute force: of ``TUNED`` members
    those that link with others must find ``AUDIT_RECALL`` of these links.
    """

    def __init__(self, rows: np.ndarray, ids: np.ndarray, weights: np.ndarray, threshold: float, beam: int):
        self.exact, self.ids, self.weights = unit_vectors(rows), ids, weights
        self.threshold, self.width = threshold, beam
        self.graph = SmallWorld(self.exact)
        self._parent = np.arange(len(ids))
        sample = np.linspace(0, len(ids) - 1, min(TUNED, len(ids))).astype(np.int64)
        truth = self.exact[sample] @ self.exact.T >= threshold
        truth[np.arange(len(sample)), sample] = False
        some = truth.any(1)
        if some.any():
            self._widen(self.exact[sample[some]], truth[some])

    def _found(self, queries: np.ndarray) -> list[np.ndarray]:
        near = self.graph.within(queries, self.threshold - SLACK, self.width)
        return [f[self.exact[f] @ q >= self.threshold] for f, q in zip(near, queries)]

    def _widen(self, queries: np.ndarray, truth: np.ndarray) -> bool:
        """Double the beam until the queries find their true links; whether it had to be."""
        start = self.width
        while self.width < len(self.ids):
            found = self._found(queries)
            if sum(int(truth[k, f].sum()) for k, f in enumerate(found)) >= AUDIT_RECALL * truth.sum():
                break
            self.width *= 2
        return self.width > start

    def links(self, queries: np.ndarray, ids: np.ndarray) -> list[np.ndarray]:
        """Positions that each query links with, its own left out; some queries of each block are audited."""
        queries = unit_vectors(queries)
        found = self._found(queries)
        sample = np.linspace(0, len(queries) - 1, min(AUDITED, len(queries))).astype(np.int64)
        truth = (queries[sample] @ self.exact.T >= self.threshold) & (self.ids[None, :] != ids[sample, None])
        seen = sum(int(truth[k, found[i]].sum()) for k, i in enumerate(sample))
        if seen < AUDIT_RECALL * truth.sum() and self._widen(queries[sample], truth):
            found = self._found(queries)
        return [f[self.ids[f] != i] for f, i in zip(found, ids)]

    def joins(self, found: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """(query, position) of links that no earlier link of this shard makes superfluous: one for each component that a query newly ties together."""
        queries, places = [], []
        for i, f in enumerate(found):
            if not len(f):
                continue
            roots = self._parent[f]
            while not np.array_equal(above := self._parent[roots], roots):
                roots = above
            self._parent[f] = roots
            distinct, first = np.unique(roots, return_index=True)
            queries += [i] * len(distinct)
            places += f[first].tolist()
            self._parent[distinct] = distinct[0]
        return np.array(queries, np.int64), np.array(places, np.int64)


def cosine_links(vectors: DataFrame, *, threshold: float = 0.95, shards: int | None = None, beam: int = SEARCH_BEAM) -> DataFrame:
    """What links with cosine ``threshold`` at least, for each row of ``vectors(id, v array<double>, weight)``.

    Rows ``id, linked``: the weight of all that the vector links with in one
    shard. Rows ``id, other``: links of a spanning forest of the shard's
    answers, so that the rows grow with the vectors and not with the pairs.
    Ids are distinct. Each shard's graph is built in one task, which then
    streams all vectors past it. Vectors of different lengths do not link.
    """

    def answer(shard: _Shard, rows: np.ndarray, ids: np.ndarray) -> pa.RecordBatch:
        found = shard.links(rows, ids)
        linked = np.array([int(shard.weights[f].sum()) for f in found])
        some = np.flatnonzero(linked)
        at, to = shard.joins(found)
        return pa.RecordBatch.from_arrays(
            [
                pa.array(np.concatenate([ids[some], ids[at]])),
                pa.array(np.concatenate([np.zeros(len(some), np.int64), shard.ids[to]]), mask=np.arange(len(some) + len(at)) < len(some)),
                pa.array(np.concatenate([linked[some], np.zeros(len(at), np.int64)])),
            ],
            names=["id", "other", "linked"],
        )

    return search_shards(vectors, vectors, lambda rows, ids, weights: _Shard(rows, ids, weights, threshold, beam), answer, "id long, other long, linked long", shards=shards)


def near_duplicate_vectors(vectors: DataFrame, *, threshold: float = 0.95, shards: int | None = None) -> DataFrame:
    """One row per row of ``vectors(vec_id, embedding)``: ``vec_id, n_links, component_id, kept``.

    Equal vectors are one class and are compared once. Vectors that are null,
    empty, zero or hold null or non-finite components, and rows without vec_id,
    link with nothing. Rows that repeat a vec_id are one vector where they are
    equal; otherwise each has its own links and they share a component.
    """
    rows = only(vectors, "vec_id", "embedding").select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"))
    good = usable(rows).where(F.col("vec_id").isNotNull()).distinct()
    classes = good.groupBy("embedding").agg(F.min("vec_id").alias("least"), F.count(F.lit(1)).alias("weight"))
    place = F.row_number().over(Window.partitionBy("least").orderBy("embedding"))
    named = F.when(place == 1, F.col("least")).otherwise(F.xxhash64("embedding"))  # classes of one vec_id have ids of their own
    classes = materialize(classes.select(named.alias("id"), "least", F.col("embedding").alias("v"), "weight"), "vector-classes")
    found = materialize(cosine_links(classes, threshold=threshold, shards=shards), "vector-links")
    tagged = rows.join(classes.select(F.col("v").alias("embedding"), "id", "least", "weight"), "embedding", "left")
    tagged = materialize(tagged.select("vec_id", F.when(F.col("vec_id").isNotNull(), F.col("id")).alias("id"), "least", "weight"), "vector-rows")

    edges = found.where(F.col("other").isNotNull()).select(F.col("id").alias("a"), F.col("other").alias("b"))
    doubled = not classes.where(F.col("id") != F.col("least")).isEmpty() or not tagged.where(F.col("id").isNotNull()).groupBy("vec_id").agg(F.min("id").alias("a"), F.max("id").alias("b")).where(F.col("a") != F.col("b")).isEmpty()
    if doubled:  # a vec_id with several vectors ties their classes
        same = tagged.where(F.col("id").isNotNull()).select("vec_id", "id")
        edges = edges.unionByName(same.join(same.groupBy("vec_id").agg(F.min("id").alias("b")), "vec_id").where(F.col("id") != F.col("b")).select(F.col("id").alias("a"), "b"))
    parts = connected_components(edges).withColumnRenamed("vertex", "id")
    if doubled:  # a class's own id may not be a vec_id
        parts = parts.join(classes.select("id", "least"), "id")
        parts = parts.select("id", "component").join(parts.groupBy("component").agg(F.min("least").alias("name")), "component").select("id", F.col("name").alias("component"))
    counts = found.where(F.col("other").isNull()).groupBy("id").agg(F.sum("linked").alias("linked"))
    known = materialize(counts.join(parts, "id", "full"), "vector-known")  # as a table, so that a hot class's rows can be split
    joined = tagged.join(known, "id", "left")
    component = F.when(F.col("vec_id").isNotNull(), F.coalesce("component", "least", "vec_id"))
    n_links = F.when(F.col("id").isNotNull(), F.coalesce("linked", F.lit(0)) + F.col("weight") - 1).otherwise(0).cast("long")
    return joined.select("vec_id", n_links.alias("n_links"), component.alias("component_id"), F.coalesce(component == F.col("vec_id"), F.lit(True)).alias("kept"))
