"""Substring deduplication: fuzzy passages by collinear chaining of word k-mers.

Seeds are the minimizers of a document's word k-mers, at every place where they
occur. Each occurrence is joined to two earlier documents that have it, the
first of the corpus and the nearest before, so a passage that thousands of
documents share costs two matches for each occurrence, and a passage put
together from older ones is still met where it stood whole. The matches of a
pair of documents are chained, in order in both, with costs for gaps, through a
Fenwick tree of prefix maxima; chains are aligned on the words of both
documents and extended beyond their seeds. Aligned passages of enough words
count as repeats of the earlier document.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treesketch.llm.storage import Columns, materialize, named_in, small_batches
from treesketch.llm.wordhash import WordHasher, mix64, shingle_hashes
from treesketch.llm.worker import forget

#: Words in a seed, and k-mers of which one is a seed: an exact run of KMER + WINDOW - 1 words has one.
KMER, WINDOW = 6, 8
#: Words that a repeated passage has at least, and the share of them that must agree.
MIN_WORDS, MIN_IDENTITY = 50, 0.8
#: Words between neighbouring seeds of a chain, at most, and the cost of each skipped word in matched words.
MAX_GAP, GAP_COST = 48, 0.1
#: Words beside a chain that are fetched for its extension: of one that is a passage by itself, and of a shorter one.
MARGIN, SHORT_MARGIN = 256, 96
#: An alignment goes on over words that differ, each at this cost in agreeing words, until it has lost so many.
MISS_COST, DROP = 2, 15
#: Words that one side may lack where an alignment goes on, and the words that must agree after them; the ways to pass over them, fewest first.
SLACK, PROOF = 4, 4
SHIFTS = sorted(((p, q) for p in range(SLACK + 1) for q in range(SLACK + 1) if p != q), key=lambda s: (max(s), sum(s)))
#: Documents of one batch with the same seed that go to the corpus-wide join each; of more, the first and the last.
HOT = 4
#: Matches that a task handles at a time.
BUFFER = 50_000

def _window_minima(order: np.ndarray, window: int) -> np.ndarray:
    """Places of the least value of each window, the first of equals, once each: minima of windows twice as long from two shorter ones."""
    at, size = np.arange(len(order)), 1
    while size < window:
        step = min(size, window - size)
        left, right = at[:-step], at[step:]
        at = np.where(order[left] <= order[right], left, right)
        size += step
    return at[np.append(True, at[1:] != at[:-1])]


def minimizers(words: np.ndarray, k: int = KMER, window: int = WINDOW) -> tuple[np.ndarray, np.ndarray]:
    """Positions and hashes of the least k-mer of each window; of all k-mers together in a shorter text."""
    if len(words) < k:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    grams = shingle_hashes(words, k)
    order = mix64(grams ^ np.uint64(0x5555555555555555))
    if len(order) <= window:
        at = np.array([int(np.argmin(order))])
    else:
        at = _window_minima(order, window)
    return at, grams[at]


def _spaced(at: np.ndarray, h: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Places and hashes without the further places of a hash in one stretch of ``window`` words, so that a word repeated on end gives few seeds."""
    order = np.lexsort((at, h))
    h, at = h[order], at[order]
    keep = np.ones(len(h), bool)
    keep[1:] = (h[1:] != h[:-1]) | (at[1:] // window != at[:-1] // window)
    return at[keep], h[keep]


class PrefixMaximum:
    """Fenwick tree: the best (value, item) at or below a rank."""

    def __init__(self, n: int):
        self._best = [(-1e18, -1)] * (n + 1)

    def raise_to(self, rank: int, value: float, item: int) -> None:
        while rank < len(self._best):
            if value > self._best[rank][0]:
                self._best[rank] = (value, item)
            rank += rank & -rank

    def at_most(self, rank: int) -> tuple[float, int]:
        best = (-1e18, -1)
        while rank > 0:
            if self._best[rank][0] > best[0]:
                best = self._best[rank]
            rank -= rank & -rank
        return best


def chain(a: np.ndarray, b: np.ndarray, k: int = KMER, gap_cost: float = GAP_COST, max_gap: int = MAX_GAP) -> list[np.ndarray]:
    """Collinear chains of the matches (a[i], b[i]): lists of indices, each match in one chain at most, best chains first.

    A chain's value is k for each match less ``gap_cost`` for each word passed
    over in either document; that splits into a term of each end, so the best
    predecessor of a match is a prefix maximum over b among smaller a.
    """
    order = np.lexsort((b, a))
    ranks = np.searchsorted(np.unique(b), b) + 1
    tree, value, before = PrefixMaximum(int(ranks.max())), {}, {}
    waiting: list[int] = []
    last_a = None
    for i in order.tolist():
        if a[i] != last_a:  # equal positions must not follow one another
            for j in waiting:
                tree.raise_to(int(ranks[j]), value[j] + gap_cost * float(a[j] + b[j]), j)
            waiting, last_a = [], a[i]
        best, j = tree.at_most(int(ranks[i]) - 1)
        gain = best - gap_cost * float(a[i] + b[i])
        linked = j >= 0 and gain > 0 and a[i] - a[j] <= max_gap + k and b[i] - b[j] <= max_gap + k
        value[i], before[i] = k + (gain if linked else 0.0), j if linked else -1
        waiting.append(i)
    used, out = set(), []
    for i in sorted(value, key=value.get, reverse=True):
        if i in used:
            continue
        steps = []
        while i >= 0 and i not in used:
            used.add(i)
            steps.append(i)
            i = before[i]
        out.append(np.array(steps[::-1]))
    return out


def _agreeing(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Which words of the short sequence x a longest common subsequence with y takes."""
    out = np.zeros(len(x), bool)
    if len(x) == len(y):
        same = x == y
        if 2 * same.sum() >= len(x):
            return same
    if not len(x) or not len(y):
        return out
    rows = np.zeros((len(x) + 1, len(y) + 1), np.int32)
    for i, word in enumerate(x):
        take = np.where(y == word, rows[i, :-1] + 1, 0)
        rows[i + 1, 1:] = np.maximum.accumulate(np.maximum(rows[i, 1:], take))
    i, j = len(x), len(y)
    while i and j:
        if rows[i, j] == rows[i - 1, j]:
            i -= 1
        elif rows[i, j] == rows[i, j - 1]:
            j -= 1
        else:
            i, j = i - 1, j - 1
            out[i] = True
    return out


def _resumed(x: np.ndarray, y: np.ndarray) -> tuple[int, int] | None:
    """The fewest words to pass over at the start of x and of y so that ``PROOF`` words agree; None if there are none."""
    x, y = x[: SLACK + PROOF].tolist(), y[: SLACK + PROOF].tolist()
    in_x, in_y = ([w[i : i + PROOF] for i in range(len(w) - PROOF + 1)] for w in (x, y))
    if not any(w in in_y for w in in_x):
        return None
    return next(((p, q) for p, q in SHIFTS if p < len(in_x) and q < len(in_y) and in_x[p] == in_y[q]), None)


def _extend(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Which words of x, from its start, agree with y in an alignment that goes on while it pays.

    Words that differ cost ``MISS_COST``; where the score has fallen by
    ``DROP`` the alignment goes back to its best end, and on from there only
    over up to ``SLACK`` words that one side lacks, if ``PROOF`` words agree
    after them.
    """
    out, i, j = [], 0, 0
    while i < len(x) and j < len(y):
        n = min(len(x) - i, len(y) - j)
        same = x[i : i + n] == y[j : j + n]
        if same[: DROP // MISS_COST + 1].any():
            score = np.cumsum(np.where(same, 1, -MISS_COST))
            fallen = np.flatnonzero(np.maximum(np.maximum.accumulate(score), 0) - score > DROP)
            score = score[: fallen[0]] if len(fallen) else score
            best = len(score) - int(score[::-1].argmax()) if len(score) and score.max() >= 0 else 0
            out.append(same[:best])
            i, j = i + best, j + best
        shift = _resumed(x[i:], y[j:])
        if shift is None:
            break
        out.append(np.zeros(shift[0], bool))
        i, j = i + shift[0], j + shift[1]
    return np.concatenate(out) if out else np.zeros(0, bool)


def align(words: np.ndarray, other: np.ndarray, a: np.ndarray, b: np.ndarray, k: int = KMER) -> tuple[int, np.ndarray]:
    """(start, agreeing) of a chain of seeds at ``a`` in ``words`` and at ``b`` in ``other``, extended both ways.

    ``agreeing`` tells for each word from ``start`` on whether it stands in the
    other document too. Seeds whose words differ, as after a clash of hashes
    or where rows repeat a doc_id, are left out; without any it is empty.
    """
    real = [(i, j) for i, j in zip(a.tolist(), b.tolist()) if i + k <= len(words) and j >= 0 and np.array_equal(words[i : i + k], other[j : j + k])]
    if not real:
        return 0, np.zeros(0, bool)
    parts, (at_a, at_b) = [], real[0]
    for i, j in real:
        if i >= at_a and j >= at_b:
            parts.append(_agreeing(words[at_a:i], other[at_b:j]))
            at_a, at_b = i, j
        if i - at_a != j - at_b:  # overlaps the last seed on another diagonal
            continue
        parts.append(np.ones(i + k - at_a, bool))
        at_a, at_b = i + k, j + k
    left = _extend(words[: real[0][0]][::-1], other[: real[0][1]][::-1])
    right = _extend(words[at_a:], other[at_b:])
    return real[0][0] - len(left), np.concatenate([left[::-1], *parts, right])


def repeated_parts(agreeing: np.ndarray, min_words: int = MIN_WORDS, min_identity: float = MIN_IDENTITY) -> list[tuple[int, int]]:
    """Ranges of an alignment that are repeats: long and alike enough, cut where ``DROP`` is lost."""
    if agreeing.all():
        return [(0, len(agreeing))] if len(agreeing) >= min_words else []
    edges = np.flatnonzero(np.diff(agreeing.astype(np.int8), prepend=0, append=0))
    out, start, score, best, end = [], None, 0, 0, 0

    def close() -> None:
        if end - start >= min_words and agreeing[start:end].sum() >= min_identity * (end - start):
            out.append((start, end))

    last = 0
    for i, j in zip(edges[0::2].tolist(), edges[1::2].tolist()):  # runs of agreeing words
        score -= MISS_COST * (i - last)
        if start is not None and best - score > DROP:
            close()
            start = None
        if start is None:
            start, score, best = i, 0, 0
        score, last = score + j - i, j
        if score >= best:
            best, end = score, j
    if start is not None:
        close()
    return out


class SeedRuns:
    """Links occurrences of seeds, given in the order of (hash, document, place), to earlier documents with the same seed."""

    def __init__(self):
        self._carried = (np.zeros(0, np.int64),) * 3

    @staticmethod
    def places(h: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of each row: where its hash begins, where its document begins in that, and the last place of the document before, or -1."""
        new_run = np.ones(len(h), bool)
        new_run[1:] = h[1:] != h[:-1]
        new_doc = new_run.copy()
        new_doc[1:] |= doc[1:] != doc[:-1]
        at = np.arange(len(h))
        run = np.maximum.accumulate(np.where(new_run, at, 0))
        group = np.maximum.accumulate(np.where(new_doc, at, 0))
        return run, group, np.where(group > run, group - 1, -1)

    @staticmethod
    def matches(doc: np.ndarray, pos: np.ndarray, run: np.ndarray, before: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, ...]:
        """(doc_id, pos, hub, hub_pos) of ``rows``: with the first document of the run, and with the one before if that is another."""
        rows = rows[before[rows] >= 0]
        second = rows[doc[before[rows]] != doc[run[rows]]]
        who, hub = np.concatenate([rows, second]), np.concatenate([run[rows], before[second]])
        return doc[who], pos[who], doc[hub], pos[hub]

    def feed(self, h: np.ndarray, doc: np.ndarray, pos: np.ndarray) -> tuple[np.ndarray, ...]:
        """Matches of the next rows; what later rows need of the last run is carried over."""
        n = len(self._carried[0])
        h, doc, pos = (np.concatenate(c) for c in zip(self._carried, (h, doc, pos)))
        run, group, before = self.places(h, doc)
        found = self.matches(doc, pos, run, before, np.arange(n, len(h)))
        last = len(h) - 1
        keep = np.unique([run[last], max(before[last], run[last]), last])
        self._carried = h[keep], doc[keep], pos[keep]
        return found


def seeds(docs: DataFrame, *, k: int = KMER, window: int = WINDOW) -> DataFrame:
    """``h, doc_id, pos, hub, hub_pos``: each document's seeds at every place; of places of one seed within one stretch of ``window`` words the first.

    Where more than ``HOT`` documents of a batch have a seed, only the first
    and the last of them are put out as seeds; the others come as matches with
    documents of the batch, ``hub`` at ``hub_pos``, and ``h`` only deals them
    out. So a seed that a third of all documents have makes few rows of one hash.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        hasher = WordHasher()
        for batch in batches:
            ids, places, hashes = [], [], []
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).cast(pa.large_binary())):
                at, h = _spaced(*minimizers(hasher.words(text.as_py() or b""), k, window), window)
                ids.append(np.full(len(h), doc_id, np.int64)), places.append(at), hashes.append(h.astype(np.int64))
            if not ids:
                continue
            doc, pos, h = (np.concatenate(c) for c in (ids, places, hashes))
            order = np.lexsort((pos, doc, h))
            doc, pos, h = doc[order], pos[order], h[order]
            start, group, before = SeedRuns.places(h, doc)
            new = group == np.arange(len(h))
            docs_before = np.cumsum(new) - np.cumsum(new)[start] if len(h) else group
            ends = np.append(np.flatnonzero(np.diff(start)), len(h) - 1) if len(h) else start
            most = np.zeros(len(h), np.int64)
            most[start[ends]] = docs_before[ends]
            most = most[start]  # documents with the row's seed, less one
            inner = (most >= HOT) & (docs_before > 0) & (docs_before < most)
            local = SeedRuns.matches(doc, pos, start, before, np.flatnonzero(inner))
            dealt = mix64((local[0] * 3 + local[2]).astype(np.uint64)).astype(np.int64)
            n = len(h) - int(inner.sum())
            columns = [np.concatenate(c) for c in ((h[~inner], dealt), (doc[~inner], local[0]), (pos[~inner], local[1]), (np.zeros(n, np.int64), local[2]), (np.zeros(n, np.int64), local[3]))]
            seed = np.arange(len(columns[0])) < n
            for at in range(0, len(seed), BUFFER):
                cut = slice(at, at + BUFFER)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(columns[0][cut]), pa.array(columns[1][cut]), pa.array(columns[2][cut].astype(np.int32)), pa.array(columns[3][cut], mask=seed[cut]), pa.array(columns[4][cut].astype(np.int32), mask=seed[cut])],
                    names=["h", "doc_id", "pos", "hub", "hub_pos"],
                )

    rows = docs.where(F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return rows.mapInArrow(run, "h long, doc_id long, pos int, hub long, hub_pos int")


def seed_matches(found: DataFrame) -> DataFrame:
    """``doc_id, pos, hub, hub_pos``: each seed with the first document of the corpus that has it and with the nearest before.

    One shuffle; runs of one hash are streamed in order, whatever their length.
    """
    tasks = int(found.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ordered = found.select("h", "doc_id", "pos", "hub", "hub_pos").repartition(tasks, "h").sortWithinPartitions("h", "doc_id", "pos")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        runs, held, size = SeedRuns(), [], 0

        def linked() -> pa.RecordBatch:
            h, doc, pos, hub, hub_pos = (np.concatenate(c) for c in zip(*held))
            done = hub_pos >= 0
            columns = [np.concatenate(c) for c in zip((doc[done], pos[done], hub[done], hub_pos[done]), runs.feed(h[~done], doc[~done], pos[~done]) if not done.all() else (doc[:0],) * 4)]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int32(), pa.int64(), pa.int32()))], names=["doc_id", "pos", "hub", "hub_pos"])

        for batch in batches:
            if batch.num_rows:
                held.append([batch.column(i).to_numpy() for i in range(3)] + [batch.column(i).fill_null(-1).to_numpy() for i in (3, 4)])
                size += batch.num_rows
            if size >= BUFFER:
                yield linked()
                held, size = [], 0
        if held:
            yield linked()

    return ordered.mapInArrow(run, "doc_id long, pos int, hub long, hub_pos int")


def chains(matches: DataFrame, *, k: int = KMER) -> DataFrame:
    """``doc_id, hub, a array<int>, b array<int>`` for each chain of seeds of two documents.

    Matches of a pair number at most the seeds of a document. Of a chain
    without shifts only the first and the last seed are kept.
    """
    tasks = int(matches.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    order = ["doc_id", "hub", "pos", "hub_pos"]
    ranged = matches.select(*order).repartition(tasks, "doc_id", "hub").sortWithinPartitions(*order)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []

        def made(rows: list[np.ndarray]) -> pa.RecordBatch:
            ids, hubs, firsts, seconds = [], [], [], []
            for block in rows:
                a, b = block[:, 2], block[:, 3]
                one_line = len(block) == 1 or (int((a - b).min()) == int((a - b).max()) and int(np.diff(a).max()) <= MAX_GAP)
                for steps in [np.arange(len(a))] if one_line else chain(a, b, k):
                    x, y = a[steps], b[steps]
                    if len(x) > 2 and int((x - y).min()) == int((x - y).max()):
                        x, y = x[[0, -1]], y[[0, -1]]
                    ids.append(int(block[0, 0])), hubs.append(int(block[0, 1])), firsts.append(x), seconds.append(y)
            return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(hubs, pa.int64()), pa.array(firsts, pa.list_(pa.int32())), pa.array(seconds, pa.list_(pa.int32()))], names=["doc_id", "hub", "a", "b"])

        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(np.column_stack([batch.column(i).to_numpy() for i in range(4)]).astype(np.int64))
            if len(held) > 1 and np.array_equal(held[0][0, :2], held[-1][-1, :2]):
                continue  # still the same pair
            rows = np.concatenate(held)
            blocks = np.split(rows, np.flatnonzero((np.diff(rows[:, 0]) != 0) | (np.diff(rows[:, 1]) != 0)) + 1)
            held = [blocks[-1]]
            if len(blocks) > 1:
                yield made(blocks[:-1])
        if held:
            yield made([np.concatenate(held)])

    return ranged.mapInArrow(run, "doc_id long, hub long, a array<int>, b array<int>")


def _words_of(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """``hub, words binary``: 32-bit word hashes of the documents named in ``ids(id)``; a row for each row of such a document."""
    rows = named_in(docs.select("doc_id", "text"), ids, "doc_id").select(F.col("doc_id").cast("long").alias("hub"), "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        hasher = WordHasher()
        for batch in batches:
            for start in range(0, batch.num_rows, 512):
                part = batch.slice(start, 512)
                words = [(hasher.words(t.as_py() or b"") >> np.uint64(32)).astype("<u4").tobytes() for t in part.column(1).cast(pa.large_binary())]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(words, pa.binary())], names=["hub", "words"])

    return rows.mapInArrow(run, "hub long, words binary")


def chains_with_words(docs: DataFrame, found: DataFrame, *, k: int = KMER, min_words: int = MIN_WORDS) -> DataFrame:
    """Adds to each chain ``from_word, words``: the other document's words around it.

    Both sides of the join are dealt out by the other document alone, so that
    adaptive execution can split one that very many chains name.
    """
    margin = F.when(F.element_at("b", -1) - F.element_at("b", 1) >= min_words, MARGIN).otherwise(SHORT_MARGIN)
    low = F.greatest(F.element_at("b", 1) - margin, F.lit(0))
    length = F.element_at("b", -1) + k + margin - low
    joined = found.join(_words_of(docs, found.select(F.col("hub").alias("id")).distinct()), "hub")
    return joined.select("doc_id", "hub", "a", "b", low.alias("from_word"), F.substring("words", low * 4 + 1, length * 4).alias("words"))


class RepeatCutter:
    """Takes repeated passages out of texts."""

    def __init__(self, k: int = KMER, min_words: int = MIN_WORDS, min_identity: float = MIN_IDENTITY):
        self.k, self.min_words, self.min_identity = k, min_words, min_identity
        self.hasher = WordHasher()

    def spans(self, words: np.ndarray, rows: list[dict]) -> list[dict]:
        """Repeats in ``words`` by the chains in ``rows``, longest chains first; what is covered already is not aligned again."""
        out: list[dict] = []
        for row in sorted(rows, key=lambda r: (r["a"][0] - r["a"][-1], r["hub"], r["a"][0])):
            a, b = np.array(row["a"]), np.array(row["b"]) - row["from_word"]
            if any(s["start"] <= a[0] and a[-1] + self.k <= s["end"] for s in out):
                continue
            start, agreeing = align(words, np.frombuffer(row["words"], "<u4"), a, b, self.k)
            out += [{"start": start + i, "end": start + j, "doc_id": row["hub"]} for i, j in repeated_parts(agreeing, self.min_words, self.min_identity)]
        return sorted(out, key=lambda s: (s["start"], s["end"], s["doc_id"]))

    def cut(self, text: bytes, rows: list[dict]) -> tuple[bytes, int, int, list[dict]]:
        """(text that is left, words, words removed, spans)."""
        words = (self.hasher.words(text) >> np.uint64(32)).astype(np.uint32)
        spans = self.spans(words, rows)
        if not spans:
            return text, len(words), 0, []
        gone = np.zeros(len(words) + 1, np.int64)
        for s in spans:
            gone[s["start"]] += 1
            gone[s["end"]] -= 1
        left = np.cumsum(gone[:-1]) == 0
        first, last = self.hasher.spans(text)
        edge = np.diff(left.astype(np.int8), prepend=0, append=0)
        parts = [text[first[i] : last[j - 1]] for i, j in zip(np.flatnonzero(edge == 1), np.flatnonzero(edge == -1))]
        return b"\n".join(parts), len(words), int((~left).sum()), spans


ADDED = ("n_words", "n_removed", "spans")


def remove_repeats(docs: DataFrame, *, min_words: int = MIN_WORDS, min_identity: float = MIN_IDENTITY, k: int = KMER, window: int = WINDOW) -> DataFrame:
    """``docs`` without passages that repeat an earlier document, and ``n_words, n_removed, spans``.

    ``spans`` are the removed ranges of words (start, end, an earlier doc_id
    that has them). A passage stays in the document with the smallest doc_id.
    Words are compared lower-cased; what is left keeps its characters. Rows
    without doc_id, and null and empty texts, stay as they are; rows that
    repeat a doc_id are one document and do not lose text to each other, but
    each loses what an earlier document has. Given columns of the three added
    names, in any case, make way for them; all others pass through.
    """
    small_batches(docs.sparkSession)
    given = Columns(docs)
    frame, text = given.frame, given["text"]
    slim = frame.select(F.col(given["doc_id"]).alias("doc_id"), F.col(text).alias("text"))
    linked = materialize(chains(seed_matches(seeds(slim, k=k, window=window)), k=k), "chains")
    chain_row = F.struct("hub", "a", "b", "from_word", "words")
    per_doc = chains_with_words(slim, linked, k=k, min_words=min_words).groupBy(F.col("doc_id").alias("id")).agg(F.collect_list(chain_row).alias("rows"))

    places = given.others(ADDED)
    at = places.index(given.place("text"))
    names = [f"_{i}" for i in places]
    owners = linked.select(F.col("doc_id").alias("id")).distinct()
    touched = named_in(frame, owners, given["doc_id"]).join(per_doc, F.col(given["doc_id"]).cast("long") == F.col("id")).select(*names, "rows")
    free = named_in(frame, owners, given["doc_id"], "left_anti").select(*names, F.lit(None).cast(touched.schema["rows"].dataType).alias("rows"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        cutter = RepeatCutter(k, min_words, min_identity)
        span_type = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("doc_id", pa.int64())]))
        for whole in batches:
            for start in range(0, whole.num_rows, 256):
                batch = whole.slice(start, 256)
                texts, results = [], []
                for text, rows in zip(batch.column(at).to_pylist(), batch.column(len(places)).to_pylist()):
                    raw = (text or "").encode()
                    left, *rest = cutter.cut(raw, rows) if rows else (raw, len(cutter.hasher.spans(raw)[0]) if raw else 0, 0, [])
                    texts.append(left.decode() if rest[2] else text)
                    results.append(rest)
                arrays = [pa.array(texts, pa.string()) if i == at else batch.column(i) for i in range(len(places))]
                yield pa.RecordBatch.from_arrays([*arrays, *[pa.array(c, t) for c, t in zip(zip(*results), (pa.int64(), pa.int64(), span_type))]], names=[*names, *ADDED])

    fields = ", ".join(f"_{i} {given.types[i]}" for i in places)
    schema = f"{fields}, n_words long, n_removed long, spans array<struct<start:bigint,end:bigint,doc_id:bigint>>"
    return given.named(touched.mapInArrow(run, schema).unionByName(free.mapInArrow(run, schema)), places, ADDED)
