"""Quality classifier: a factorisation machine over words, structure and length.

A document's features are hashed words (log counts, unit length together),
statistics of its form, and its length. The score adds a bias, linear weights
and low-rank interactions of all pairs of features; with the identity
sum_{i<j} <v_i,v_j> x_i x_j = (|sum_i v_i x_i|^2 - sum_i |v_i|^2 x_i^2) / 2
that takes time linear in the features.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treesketch.llm.storage import Columns, small_batches
from treesketch.llm.wordhash import WordHasher
from treesketch.llm.worker import forget

WORD_BUCKETS = 1 << 14
RANK = 6
#: Labelled rows that a model is fitted on at most; which ones, a hash of the id decides.
MAX_FIT_ROWS = 12_000
EPOCHS = 6
#: Names of the statistics, in the order of their features.
STATISTICS = (
    "log_bytes", "log_words", "mean_word", "upper", "digits", "punctuation", "symbols", "bars", "non_ascii", "spaces", "distinct_words", "top_word", "second_word",
    "repeated_pairs", "capital_words", "mean_line", "repeated_lines", "ends_of_sentences", "short_words", "long_words",
)


class Features:
    """Sparse features of whole texts: statistics first, then word buckets."""

    def __init__(self, buckets: int = WORD_BUCKETS):
        self.buckets = buckets
        self._hasher = WordHasher()
        kinds = np.zeros(256, np.int64)  # 1 upper, 2 digit, 3 punctuation, 4 symbol, 5 bar, 6 not ASCII, 7 space
        kinds[65:91], kinds[48:58], kinds[128:] = 1, 2, 6
        kinds[[ord(c) for c in ".,;:!?'\"()-"]] = 3
        kinds[[ord(c) for c in "#$%&*+/<=>@[\\]^_`{}~"]] = 4
        kinds[ord("|")] = 5
        kinds[[32, 9, 10, 11, 12, 13]] = 7
        self._kinds = kinds
        self._sentence = re.compile(rb"[.!?](?=\s|$)").findall

    def of(self, text: str | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(statistics, buckets of distinct words, their values)."""
        raw = (text or "").encode()
        n = max(1, len(raw))
        data = np.frombuffer(raw, np.uint8)
        kinds = np.bincount(self._kinds[data], minlength=8) if len(data) else np.zeros(8, np.int64)
        words = self._hasher.words(raw)
        m = max(1, len(words))
        distinct, counts = np.unique(words, return_counts=True)
        top = np.sort(counts)[::-1][:2] if len(counts) else np.zeros(0)
        start, end = self._hasher.spans(raw) if raw else (np.zeros(0, np.int64),) * 2
        lengths = end - start
        pairs = words[1:] * np.uint64(0x9E3779B97F4A7C15) + words[:-1] if len(words) > 1 else words[:0]
        lines = raw.split(b"\n")
        capital = self._kinds[data[start]] == 1 if len(start) else np.zeros(0, bool)
        statistics = np.array([
            np.log1p(len(raw)), np.log1p(len(words)), lengths.mean() if len(lengths) else 0.0, *(kinds[1:8] / n),
            len(distinct) / m, top[0] / m if len(top) else 0.0, top[1] / m if len(top) > 1 else 0.0,
            1 - len(np.unique(pairs)) / max(1, len(pairs)), capital.sum() / m, np.log1p(len(raw) / len(lines)), 1 - len(set(lines)) / len(lines),
            len(self._sentence(raw)) / m, (lengths <= 2).sum() / m, (lengths >= 14).sum() / m,
        ])
        bucket, at = np.unique((distinct % np.uint64(self.buckets)).astype(np.int64), return_inverse=True)
        value = np.log1p(np.bincount(at, counts, len(bucket)))
        return statistics, bucket, value / max(1e-9, np.sqrt((value * value).sum()))


@dataclass
class FactorizationMachine:
    mean: np.ndarray
    spread: np.ndarray
    bias: float
    linear: np.ndarray
    factors: np.ndarray

    def rows(self, features: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Indices, values and row starts; statistics are scaled as in the fitted sample and kept within four spreads."""
        s = len(self.mean)
        index, value = [], []
        for statistics, bucket, x in features:
            index += [np.arange(s), bucket.astype(np.int64) + s]
            value += [np.clip((statistics - self.mean) / self.spread, -4, 4) / 2, x]  # the result has double precision
        starts = np.cumsum([0] + [s + len(b) for _, b, _ in features])
        return np.concatenate(index), np.concatenate(value), starts[:-1]

    def to_bytes(self) -> bytes:
        """Sizes, then all numbers: single precision for weights and factors, which is what a score needs."""
        head = np.array([len(self.mean), *self.factors.shape], "<i8").tobytes() + np.array([self.bias, *self.mean, *self.spread], "<f8").tobytes()
        return head + self.linear.astype("<f4").tobytes() + self.factors.astype("<f4").tobytes()

    @classmethod
    def from_bytes(cls, raw: bytes) -> FactorizationMachine:
        s, n, rank = np.frombuffer(raw, "<i8", 3).tolist()
        head = np.frombuffer(raw, "<f8", 1 + 2 * s, 24)
        rest = np.frombuffer(raw, "<f4", n * (1 + rank), 24 + 8 * (1 + 2 * s)).astype(np.float64)
        return cls(head[1 : 1 + s], head[1 + s :], float(head[0]), rest[:n], rest[n:].reshape(n, rank))

    def margins(self, index: np.ndarray, value: np.ndarray, starts: np.ndarray) -> np.ndarray:
        vx = self.factors[index] * value[:, None]
        sums = np.add.reduceat(vx, starts)
        squares = np.add.reduceat((vx * vx).sum(1), starts)
        return self.bias + np.add.reduceat(self.linear[index] * value, starts) + 0.5 * ((sums * sums).sum(1) - squares)

    def score(self, features: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> np.ndarray:
        """Probability of label 1 for each document."""
        if not features:
            return np.zeros(0)
        return 1 / (1 + np.exp(-np.clip(self.margins(*self.rows(features)), -30, 30)))


def fit(features: list[tuple[np.ndarray, np.ndarray, np.ndarray]], labels: np.ndarray, *, buckets: int = WORD_BUCKETS, rank: int = RANK, epochs: int = EPOCHS, rate: float = 0.05, decay: float = 1e-4, seed: int = 1) -> FactorizationMachine:
    """Logistic loss by AdaGrad in small batches. Without both labels the score is the smoothed share of label 1."""
    labels = np.asarray(labels, np.float64)
    share = (labels.sum() + 1) / (len(labels) + 2)
    stats = np.array([f[0] for f in features]) if features else np.zeros((1, len(STATISTICS)))
    rng = np.random.default_rng(seed)
    n = stats.shape[1] + buckets
    model = FactorizationMachine(stats.mean(0), np.maximum(stats.std(0), 1e-6), float(np.log(share / (1 - share))), np.zeros(n), rng.normal(0, 0.01, (n, rank)))
    if len(set(labels.tolist())) < 2:
        return model
    g_bias, g_linear, g_factors = 1e-6, np.full(n, 1e-6), np.full((n, rank), 1e-6)
    batch = 128
    for _ in range(epochs):
        order = rng.permutation(len(features))
        for at in range(0, len(order), batch):
            take = order[at : at + batch]
            index, value, starts = model.rows([features[i] for i in take])
            row = np.repeat(np.arange(len(take)), np.diff(np.append(starts, len(index))))
            p = 1 / (1 + np.exp(-np.clip(model.margins(index, value, starts), -30, 30)))
            slope = (p - labels[take]) / len(take)
            vx = model.factors[index] * value[:, None]
            sums = np.add.reduceat(vx, starts)
            weight = slope[row] * value
            touched, where = np.unique(index, return_inverse=True)
            d_linear = np.bincount(where, weight, len(touched)) + decay * model.linear[touched]
            d_each = weight[:, None] * (sums[row] - vx)
            d_factors = np.stack([np.bincount(where, d_each[:, f], len(touched)) for f in range(rank)], 1) + decay * model.factors[touched]
            g_linear[touched] += d_linear**2
            g_factors[touched] += d_factors**2
            g_bias += slope.sum() ** 2
            model.linear[touched] -= rate * d_linear / np.sqrt(g_linear[touched])
            model.factors[touched] -= rate * d_factors / np.sqrt(g_factors[touched])
            model.bias -= rate * slope.sum() / np.sqrt(g_bias)
    return model


def labelled_sample(docs: DataFrame, labels: DataFrame, *, held_out: int = 2, folds: int = 4, limit: int = MAX_FIT_ROWS) -> DataFrame:
    """``text, label`` of at most ``limit`` labelled rows outside the held-out fold, those with the least hash of the id."""
    ids = labels.where(F.col("doc_id").isNotNull() & F.col("label").isNotNull() & (F.crc32(F.col("doc_id").cast("string")) % folds != held_out))
    ids = ids.groupBy("doc_id").agg(F.max("label").alias("label")).orderBy(F.xxhash64(F.lit(3), "doc_id"), "doc_id").limit(limit)
    return docs.join(F.broadcast(ids.select("doc_id", F.col("label").alias("_label"))), "doc_id").select("text", F.col("_label").alias("label"))


def fit_quality(docs: DataFrame, labels: DataFrame, **options) -> FactorizationMachine:
    """Fit on ``docs(doc_id, text)`` and ``labels(doc_id, label)``; other columns do not matter.

    Features are taken where the texts lie; a row of the sample, which
    MAX_FIT_ROWS bounds, is some hundred numbers. One executor task gathers
    them, sorts them, so that the model does not depend on the partitioning,
    and fits. What comes to the driver is the model, of fixed size.
    """
    small_batches(docs.sparkSession)
    given, marks = Columns(docs), Columns(labels)
    ids = marks.frame.select(F.col(marks["doc_id"]).cast("long").alias("doc_id"), F.col(marks["label"]).alias("label"))
    sample = labelled_sample(given.frame.select(F.col(given["doc_id"]).cast("long").alias("doc_id"), F.col(given["text"]).alias("text")), ids)

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        maker = Features()
        for batch in batches:
            rows = [maker.of(t) for t in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [pa.array([s.tobytes() for s, _, _ in rows], pa.binary()), pa.array([b.astype("<u4").tobytes() for _, b, _ in rows], pa.binary()), pa.array([v.astype("<f4").tobytes() for _, _, v in rows], pa.binary()), batch.column(1)],
                names=["s", "b", "v", "label"],
            )

    def fitted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        rows = sorted(row for batch in batches for row in zip(*(batch.column(i).to_pylist() for i in range(4))))
        features = [(np.frombuffer(s, "<f8"), np.frombuffer(b, "<u4"), np.frombuffer(v, "<f4")) for s, b, v, _ in rows]  # views, no copies
        yield pa.RecordBatch.from_arrays([pa.array([fit(features, np.array([r[3] for r in rows]), **options).to_bytes()], pa.binary())], names=["model"])

    rows = sample.select("text", F.col("label").cast("int").alias("label")).mapInArrow(made, "s binary, b binary, v binary, label int")
    found = rows.repartition(1).mapInArrow(fitted, "model binary").collect()
    return FactorizationMachine.from_bytes(bytes(found[0]["model"])) if found else fit([], np.zeros(0), **options)


def score_quality(docs: DataFrame, model: FactorizationMachine) -> DataFrame:
    """``docs`` with ``score`` in 0..1 for each whole text; null and empty texts are scored as such. The model has a fixed size.

    A given column ``score``, in any case, makes way for it; all others pass through.
    """
    small_batches(docs.sparkSession)
    given = Columns(docs)
    places = given.others(("score",))
    text = places.index(given.place("text"))
    raw = model.to_bytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        model = FactorizationMachine.from_bytes(raw)
        maker = Features(len(model.linear) - len(model.mean))
        for batch in batches:
            texts = batch.column(text)
            scores = []
            for at in range(0, len(texts), 256):
                scores.append(model.score([maker.of(t.as_py()) for t in texts[at : at + 256]]))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.concatenate(scores) if scores else np.zeros(0))], names=[*batch.schema.names, "score"])

    fields = ", ".join(f"_{i} {given.types[i]}" for i in places)
    scored = given.frame.select(*[f"_{i}" for i in places]).mapInArrow(run, f"{fields}, score double")
    return given.named(scored, places, ("score",))
