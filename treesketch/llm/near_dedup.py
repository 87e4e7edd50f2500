"""Near-duplicate documents: an inverted join of MinHash signatures on their coordinates.

A document is posted under (coordinate, value) pairs of its signature. Two
documents whose word shingles have a Jaccard similarity s agree on a coordinate
with probability s, so similar ones agree on at least ``least_matches`` of n.
Values that one document alone has are dropped; of the rest, in the order of
rarity, only a prefix is posted such that documents with that many agreements
still meet, which leaves the values of frequent passages aside. Where two
documents meet, the collisions of their whole signatures (``COUNTED``
coordinates, a byte each) are counted, and pairs whose sizes or collisions
cannot reach the threshold are skipped. What remains is confirmed on the full
shingle sets.

Documents with equal sets are one class from the start. The members of a list
are compared with a few hubs of it first, and these links are joined to
components. Lists that then still hold several components are searched again,
each document outside the list's largest component against all others; what
comes out is one row for each document and component that it may belong to,
never a pair of members, and that is confirmed against blocks of the component.
Where a list has many such rows for the documents in it, as among texts that
are alike but below the threshold, it gives the components that they join as
stars instead, and these crowds are compared as a whole, in blocks. So a large
group makes about as many rows as it has members, and no link that could join
two components is left out.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from treesketch.llm.components import FOREST_EDGES, connected_components, star_forest
from treesketch.llm.storage import materialize, named_in, only, small_batches
from treesketch.llm.wordhash import WordHasher, mix64, odd_constants, shingle_hashes
from treesketch.llm.worker import forget

#: Coordinates under which documents are posted, and those whose collisions are counted where they meet.
COORDINATES, COUNTED = 32, 128
#: The share of pairs exactly at the threshold that may have fewer matches than are asked for.
MISSED = 1e-5
#: Hubs of a list that all its members are compared with before any other pair.
HUBS = 3
#: Rows of a list that one task joins; longer lists are split.
LIST_ROWS = 512
#: Candidates of a list for each document and component in them, at most; of more come the components that they join.
FEW = 2


def least_matches(coordinates: int, percent: int) -> int:
    """The most matches to ask for so that a pair at ``percent`` of similarity has fewer with a probability of ``MISSED`` at most."""
    s, below, m = percent / 100, 0.0, 0
    while m < coordinates:
        below += math.comb(coordinates, m) * s**m * (1 - s) ** (coordinates - m)
        if below > MISSED:
            break
        m += 1
    return max(1, m)


class Signer:
    """Signatures of shingle sets: the posted coordinates as longs, and a byte of each counted one."""

    def __init__(self, coordinates: int = COORDINATES, counted: int = COUNTED):
        self._factor, self._shift = odd_constants(coordinates, 31)[:, None], odd_constants(coordinates, 37)[:, None]
        self._place = odd_constants(coordinates, 41)
        more = counted - coordinates  # these are only counted, so half the bits do
        self._factor32, self._shift32 = ((odd_constants(more, k) >> np.uint64(16)).astype(np.uint32)[:, None] | np.uint32(k == 43) for k in (43, 47))
        self._place32 = odd_constants(more, 53)

    def __call__(self, shingles: np.ndarray) -> tuple[np.ndarray, bytes]:
        least = np.full(len(self._place), np.iinfo(np.uint64).max)
        least32 = np.full(len(self._place32), np.iinfo(np.uint32).max)
        half = (shingles >> np.uint64(32)).astype(np.uint32)
        for at in range(0, len(shingles), 1024):
            least = np.minimum(least, (shingles[at : at + 1024] * self._factor + self._shift).min(1))
            least32 = np.minimum(least32, (half[at : at + 1024] * self._factor32 + self._shift32).min(1))
        posted = mix64(least + self._place)
        return posted.astype(np.int64), np.concatenate([posted, mix64(least32.astype(np.uint64) + self._place32)]).astype(np.uint8).tobytes()


def signatures(docs: DataFrame, *, size: int = 5) -> DataFrame:
    """``doc_id, n_shingles, f1, f2, sig, packed``; the last four are null for an empty set. Equal sets have equal (f1, f2, n_shingles)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        hasher, sign = WordHasher(), Signer()
        for batch in batches:
            rows = []
            for text in batch.column(1).cast(pa.large_binary()):
                shingles = np.unique(shingle_hashes(hasher.words(text.as_py() or b""), size))
                if not len(shingles):
                    rows.append((0, None, None, None, None))
                    continue
                sig, packed = sign(shingles)
                rows.append((len(shingles), int(np.bitwise_xor.reduce(shingles).astype(np.int64)), int(mix64(shingles + np.uint64(5)).sum(dtype=np.uint64).astype(np.int64)), sig, packed))
            types = (pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * 5, types)]], names=["doc_id", "n_shingles", "f1", "f2", "sig", "packed"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n_shingles long, f1 long, f2 long, sig array<bigint>, packed binary")


def _sets(docs: DataFrame, ids: DataFrame, size: int) -> DataFrame:
    """``id, members binary``: sorted shingle hashes of the documents named in ``ids(id)``."""
    rows = named_in(docs.select("doc_id", "text"), ids, "doc_id").select(F.col("doc_id").cast("long").alias("id"), "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        hasher = WordHasher()
        for batch in batches:
            members = [np.unique(shingle_hashes(hasher.words(t.as_py() or b""), size)).tobytes() for t in batch.column(1).cast(pa.large_binary())]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(members, pa.binary())], names=["id", "members"])

    return rows.mapInArrow(run, "id long, members binary").distinct()


def confirmed(docs: DataFrame, pairs: DataFrame, *, size: int = 5, percent: int = 75) -> DataFrame:
    """The rows of ``pairs(a, b)`` with 100 * intersection >= ``percent`` * union on full sets."""
    ids = pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct()
    sets = materialize(_sets(docs, ids, size), "sets")
    left, right = sets.select(F.col("id").alias("a"), F.col("members").alias("x")), sets.select(F.col("id").alias("b"), F.col("members").alias("y"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3)):
                x, y = (np.frombuffer(v.as_buffer(), np.uint64) for v in (x, y))
                both = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(100 * both >= percent * (len(x) + len(y) - both))
            yield batch.select([0, 1]).filter(pa.array(keep, pa.bool_()))

    return pairs.select("a", "b").join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(run, "a long, b long")


def _postings(classes: DataFrame, matches: int) -> DataFrame:
    """``token, df, cls``: the rarest values of each class that other classes have too."""
    tokens = classes.select("cls", F.explode("sig").alias("token"))
    shared = materialize(tokens.groupBy("token").agg(F.count(F.lit(1)).alias("df")).where(F.col("df") >= 2), "tokens")  # as a table, so that the join can split hot values
    ranked = tokens.join(shared, "token").groupBy("cls").agg(F.array_sort(F.collect_set(F.struct("df", "token"))).alias("t")).where(F.size("t") >= matches)
    return ranked.select("cls", F.explode(F.slice("t", F.lit(1), F.size("t") - (matches - 1))).alias("t")).select("t.token", "t.df", "cls")


def _part(rows: Column) -> tuple[Column, Column]:
    """(part of a list of so many rows that a class goes to, all parts), for joins of a list with itself or its hubs."""
    parts = F.ceil(rows / LIST_ROWS).cast("long")
    return F.pmod(F.xxhash64("cls"), parts), F.sequence(F.lit(0).cast("long"), parts - 1)


def _bytes(column: pa.Array) -> np.ndarray:
    """Packed signatures, a row each."""
    return np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(len(column), -1)


def _with_hubs(postings: DataFrame, signed: DataFrame, hubs: int, percent: int) -> DataFrame:
    """``a, b``: members of lists with hubs of theirs, where their signatures collide often enough."""
    hub = lambda k: F.min_by("cls", F.xxhash64(F.lit(k), "cls")) if k else F.min("cls")
    lists = postings.groupBy("token").agg(F.array_distinct(F.array(*[hub(k) for k in range(hubs)])).alias("hubs"), F.count(F.lit(1)).alias("rows"), F.first("df").alias("df")).where(F.col("rows") >= 2)
    part, parts = _part(F.col("df"))
    split = lists.select("token", "hubs", F.explode(parts).alias("part"))
    met = postings.withColumn("part", part).join(split.hint("merge"), ["token", "part"]).select("cls", F.explode("hubs").alias("hub")).where(F.col("cls") != F.col("hub"))
    pairs = met.select(F.least("cls", "hub").alias("a"), F.greatest("cls", "hub").alias("b")).distinct()
    left, right = (signed.select(F.col("cls").alias(c), F.col("n").alias(f"n_{c}"), F.col("packed").alias(f"p_{c}")).hint("merge") for c in "ab")
    joined = pairs.join(left, "a").join(right, "b").where(100 * F.least("n_a", "n_b") >= percent * F.greatest("n_a", "n_b"))
    least = least_matches(COUNTED, percent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield batch.select([0, 1]).filter(pa.array((_bytes(batch.column(2)) == _bytes(batch.column(3))).sum(1) >= least))

    return joined.select("a", "b", "p_a", "p_b").mapInArrow(run, "a long, b long")


def _open_lists(postings: DataFrame, labels: DataFrame) -> DataFrame:
    """``token, rows, major, cls, comp`` of lists that hold several components; ``major`` has most of the list."""
    named = postings.select("token", "cls").join(labels.withColumnRenamed("vertex", "cls"), "cls", "left").select("token", "cls", F.coalesce("component", "cls").alias("comp"))
    named = materialize(named, "named")
    sizes = named.groupBy("token", "comp").agg(F.count(F.lit(1)).alias("k"))
    mixed = sizes.groupBy("token").agg(F.max_by("comp", F.struct("k", "comp")).alias("major"), F.count(F.lit(1)).alias("comps"), F.sum("k").alias("rows")).where(F.col("comps") >= 2)
    return named.join(materialize(mixed.select("token", "major", "rows"), "mixed"), "token")


def _few_or_stars(met: list[tuple[int, int, np.ndarray]]) -> tuple[np.ndarray | None, np.ndarray, np.ndarray]:
    """``cls, comp, other`` of a list's candidates (cls, comp, others) if they are few; else no cls, and stars of the components that they join."""
    counts = [len(others) for *_, others in met]
    cls, comp = (np.repeat(np.array([m[i] for m in met], np.int64), counts) for i in (0, 1))
    other = np.concatenate([others for *_, others in met])
    if len(other) <= FEW * (len(met) + len(np.unique(other))):
        return cls, comp, other
    return None, *star_forest(comp, other)


def _near_components(lists: DataFrame, signed: DataFrame, ids: DataFrame, percent: int) -> DataFrame:
    """``cls, comp, other``: classes with each other component of which a member shares a list and enough of the signature.

    A task holds a part of a list, sorted by size, and streams the list's
    classes outside its major component past it; what it puts out is one row
    for each class and component. Of two components neither of which is the
    major one the smaller asks. Rows without ``cls`` join components into
    crowds, see ``_few_or_stars``.
    """
    part, parts = _part(F.col("rows"))
    rows = materialize(lists.join(ids, ["cls", "comp"]).join(signed.hint("merge"), "cls"), "open")
    columns = ["token", "part", "is_query", "n", "cls", "comp", "size", "major", "packed"]
    held = rows.withColumn("part", part).withColumn("is_query", F.lit(0)).select(*columns)
    asked = rows.where(F.col("comp") != F.col("major")).withColumn("part", F.explode(parts)).withColumn("is_query", F.lit(1)).select(*columns)
    tasks = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    placed = held.unionByName(asked).repartition(tasks, "token", "part").sortWithinPartitions("token", "part", "is_query", "n", "cls")
    least = least_matches(COUNTED, percent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, held, index, met, waiting = None, [], None, [], 0
        found: set[tuple[int | None, int, int]] = set()

        def close() -> None:
            nonlocal met, waiting
            if met:
                cls, comp, other = _few_or_stars(met)
                found.update(zip([None] * len(comp) if cls is None else cls.tolist(), comp.tolist(), other.tolist()))
                met, waiting = [], 0

        def made() -> pa.RecordBatch:
            out = pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*found)], names=["cls", "comp", "other"])
            found.clear()
            return out

        for batch in batches:
            for token, part, is_query, n, cls, comp, size, major, packed in zip(*(batch.column(i).to_pylist() for i in range(9))):
                if (token, part) != at:
                    close()
                    at, held, index = (token, part), [], None
                if not is_query:
                    held.append((n, comp, size, packed))
                    continue
                if not held:
                    continue
                if index is None:
                    sizes, comps, weights, raw = zip(*held)
                    index = np.array(sizes), np.array(comps), np.array(weights), np.frombuffer(b"".join(raw), np.uint8).reshape(len(raw), -1)
                sizes, comps, weights, signs = index
                low, high = np.searchsorted(100 * sizes, percent * n), np.searchsorted(percent * sizes, 100 * n, "right")
                others, weights = comps[low:high], weights[low:high]
                asks = (others != comp) & ((others == major) | (size < weights) | ((size == weights) & (comp < others)))
                near = np.unique(others[asks][(signs[low:high][asks] == np.frombuffer(packed, np.uint8)).sum(1) >= least])
                if len(near):
                    met.append((cls, comp, near))
                    waiting += len(near)
                    if waiting >= FOREST_EDGES:
                        close()
            if found:
                yield made()
        close()
        if found:
            yield made()

    return placed.mapInArrow(run, "cls long, comp long, other long").distinct()


def _crowds(asked: DataFrame, ids: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The members of each crowd of ``asked`` as ``cls, comp, size`` with the crowd as comp, and those outside its largest component as ``cls, other``."""
    joined = connected_components(asked.where(F.col("cls").isNull()).select(F.col("comp").alias("a"), F.col("other").alias("b")))
    named = materialize(joined.select(F.col("vertex").alias("comp"), F.col("component").alias("crowd")), "crowds")
    members = ids.join(named, "comp")
    largest = members.groupBy("crowd").agg(F.max_by("comp", F.struct("size", "comp")).alias("largest"), F.count(F.lit(1)).alias("all"))
    members = materialize(members.join(largest, "crowd"), "members")
    return members.select("cls", F.col("crowd").alias("comp"), F.col("all").alias("size")), members.where(F.col("comp") != F.col("largest")).select("cls", F.col("crowd").alias("other"))


#: Members of a component that are compared with a document at a time.
COMPONENT_BLOCK = 512


def _links_to_components(sets: DataFrame, ids: DataFrame, asked: DataFrame, percent: int) -> DataFrame:
    """``a, b``: links that join all that each document of ``asked(cls, other)`` links with in that component.

    Components are cut into blocks; a task holds a block's sets, sorted by
    shingle, and streams the documents asked past it. Only links come out, and
    of those found at a time the stars that join the same documents.
    """
    blocks = F.ceil(F.col("size") / COMPONENT_BLOCK).cast("int")
    targets = asked.select(F.col("other").alias("comp")).distinct().join(ids.groupBy("comp").agg(F.max("size").alias("size")), "comp")
    members = ids.join(targets.select("comp"), "comp", "left_semi").select("comp", F.pmod(F.xxhash64("cls"), blocks.cast("long")).cast("int").alias("block"), F.lit(0).alias("is_query"), F.col("cls").alias("id"))
    queries = asked.withColumnRenamed("other", "comp").join(targets, "comp").select("comp", F.explode(F.sequence(F.lit(0), blocks - 1)).alias("block"), F.lit(1).alias("is_query"), F.col("cls").alias("id"))
    tasks = int(sets.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    order = ["comp", "block", "is_query", "id"]
    placed = members.unionByName(queries).join(sets, "id").select(*order, "members").repartition(tasks, "comp", "block").sortWithinPartitions(*order)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, held, index = None, [], None

        def built() -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
            sizes = np.array([len(h) for _, h in held])
            flat, owner = np.concatenate([h for _, h in held]), np.repeat(np.arange(len(held)), sizes)
            by = np.argsort(flat, kind="stable")
            return np.array([i for i, _ in held]), sizes, flat[by], owner[by]

        for batch in batches:
            found_a, found_b = [], []
            for comp, block, is_query, doc, raw in zip(*(batch.column(i).to_pylist() for i in range(4)), batch.column(4)):
                if (comp, block) != at:
                    at, held, index = (comp, block), [], None
                h = np.frombuffer(raw.as_buffer(), np.uint64)
                if not is_query:
                    held.append((doc, h))
                    continue
                if not held:
                    continue
                if index is None:
                    index = built()
                names, sizes, flat, owner = index
                low, high = np.searchsorted(flat, h, "left"), np.searchsorted(flat, h, "right")
                hit = low < high
                low, count = low[hit], (high - low)[hit]
                if not len(low):
                    continue
                spots = np.repeat(low - np.concatenate([[0], np.cumsum(count)[:-1]]), count) + np.arange(count.sum())
                both = np.bincount(owner[spots], minlength=len(sizes))
                near = np.flatnonzero((100 * both >= percent * (sizes + len(h) - both)) & (names != doc))
                found_a.append(np.full(len(near), doc))
                found_b.append(names[near])
            if found_a:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in star_forest(np.concatenate(found_a), np.concatenate(found_b))], names=["a", "b"])

    return placed.mapInArrow(run, "a long, b long")


def near_duplicates(docs: DataFrame, *, size: int = 5, percent: int = 75, hubs: int = HUBS) -> DataFrame:
    """One row per row of ``docs(doc_id, text)``: ``doc_id, n_shingles, component_id, kept``.

    Rows that repeat a doc_id are one document, which links with all that one
    of its texts links with. Without doc_id a row takes no part: its component
    is null and ``kept`` is true. A document without words is its own
    component. Collisions decide which pairs are compared, so a pair exactly at
    the threshold is missed with a probability of about 2 * ``MISSED``.
    """
    small_batches(docs.sparkSession)
    docs = only(docs, "doc_id", "text")
    rows = materialize(signatures(docs, size=size), "signatures", whole=True)
    named = rows.where(F.col("sig").isNotNull() & F.col("doc_id").isNotNull())
    classes = named.groupBy("f1", "f2", "n_shingles").agg(F.min("doc_id").alias("cls"), F.first("sig").alias("sig"), F.first("packed").alias("packed"))
    classes = materialize(classes.withColumnRenamed("n_shingles", "n"), "classes")
    signed = classes.select("cls", "n", "packed")
    postings = materialize(_postings(classes, least_matches(COORDINATES, percent)), "postings")
    first = materialize(_with_hubs(postings, signed, hubs, percent), "pairs")
    links = materialize(confirmed(docs, first, size=size, percent=percent), "links")
    labels = materialize(connected_components(links), "labels")

    # What is left: documents of different components that meet in a list.
    lists = materialize(_open_lists(postings, labels), "lists")
    ids = lists.select("cls", "comp").distinct()
    ids = materialize(ids.join(ids.groupBy("comp").agg(F.count(F.lit(1)).alias("size")), "comp").select("cls", "comp", "size"), "members")
    asked = materialize(_near_components(lists, signed, ids, percent), "asked")
    if not asked.isEmpty():
        single = asked.where(F.col("cls").isNotNull()).select("cls", "other")
        wanted = single.select(F.col("other").alias("comp")).distinct()
        needed = single.select("cls").unionByName(ids.join(wanted, "comp", "left_semi").select("cls"))
        groups = [(ids, single)]
        if not asked.where(F.col("cls").isNull()).isEmpty():
            groups.append(_crowds(asked, ids))
            needed = needed.unionByName(groups[1][0].select("cls"))
        sets = materialize(_sets(docs, needed.distinct().withColumnRenamed("cls", "id"), size), "sets")
        more = [materialize(_links_to_components(sets, members, queries, percent), "links") for members, queries in groups]
        if not all(m.isEmpty() for m in more):
            labels = materialize(connected_components(reduce(DataFrame.unionByName, more, links)), "labels")

    known = classes.select("f1", "f2", F.col("n").alias("n_shingles"), "cls").join(labels.withColumnRenamed("vertex", "cls"), "cls", "left")
    known = known.select("f1", "f2", "n_shingles", F.coalesce("component", "cls").alias("known"))
    joined = rows.select("doc_id", "n_shingles", "f1", "f2").join(known, ["f1", "f2", "n_shingles"], "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("known", "doc_id"))
    return joined.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"))
