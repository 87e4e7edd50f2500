"""Gradients as relations, exact at weight 0, and as NumPy kernels for the training loop."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treesketch.functions.fixedpoint import UNIT, cents
from treesketch.learning.schedule import worker_of
from treesketch.sources import tables


def softmax_gradient_at_zero(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    """COORD of the softmax gradient at weight 0, times the number of classes and 2^20: whole numbers.

    At 0 every class has probability 1/C, so class c and component j have the
    sum of (1 - C [label = c]) x_j. Coordinate c (components + 1) + j; the last
    component is the bias.
    """
    c, m = tables.CLASSES, tables.COMPONENTS
    rows = tables.read_table(spark, sf_dir, "embeddings").where(F.col("label").isNotNull()).select(worker_of(F.col("vec_id"), workers).alias("worker"), F.col("vec_id").alias("key"), "label")
    x = tables.fixed_components(spark, sf_dir)
    x = x.unionByName(x.select("key").distinct().select("key", F.lit(m).cast("long").alias("j"), F.lit(UNIT).cast("long").alias("x")))
    per_label = rows.join(x, "key").groupBy("worker", "label", "j").agg(F.sum("x").alias("x"))
    classes = F.broadcast(spark.range(c).select(F.col("id").alias("cls")))
    part = F.col("x") * F.when(F.col("label") == F.col("cls"), 1 - c).otherwise(1)
    return per_label.crossJoin(classes).groupBy("worker", (F.col("cls") * (m + 1) + F.col("j")).alias("coord")).agg(F.sum(part).alias("val")).where(F.col("val") != 0)


def linear_gradient_at_zero(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    """COORD of the least-squares gradient at 0 of a line's price on quantity, discount, tax and 1: -sum(y x), whole numbers."""
    rows = tables.read_table(spark, sf_dir, "lineitem").select(
        F.pmod("l_orderkey", F.lit(workers)).cast("int").alias("worker"), F.floor(F.col("l_extendedprice") + 0.5).cast("long").alias("y"),
        F.array(F.col("l_quantity").cast("long"), cents(F.col("l_discount")), cents(F.col("l_tax")), F.lit(1).cast("long")).alias("xs"),
    )
    each = rows.select("worker", "y", F.posexplode("xs").alias("coord", "x"))
    return each.groupBy("worker", F.col("coord").cast("long").alias("coord")).agg(F.sum(-F.col("y") * F.col("x")).alias("val")).where(F.col("val") != 0)


@dataclass(frozen=True)
class Softmax:
    """Linear softmax on dense rows; coordinate c * (features + 1) + j, the last of a class its bias."""

    features: int
    classes: int

    @property
    def size(self) -> int:
        return self.classes * (self.features + 1)

    def start(self, seed: int) -> np.ndarray:
        return np.zeros(self.size)

    def scores(self, w: np.ndarray, x: np.ndarray) -> np.ndarray:
        w = w.reshape(self.classes, self.features + 1)
        return x @ w[:, :-1].T + w[:, -1]

    def gradient(self, w: np.ndarray, x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, float]:
        """Mean gradient and mean loss of a batch."""
        p, loss = _softmax(self.scores(w, x), y)
        p[np.arange(len(y)), y] -= 1
        p /= len(y)
        return np.concatenate([p.T @ x, p.sum(0)[:, None]], axis=1).ravel(), loss


@dataclass(frozen=True)
class Perceptron:
    """One hidden layer of rectified units before the softmax."""

    features: int
    hidden: int
    classes: int

    @property
    def size(self) -> int:
        return self.hidden * (self.features + 1) + self.classes * (self.hidden + 1)

    def start(self, seed: int) -> np.ndarray:
        rng = np.random.default_rng(seed)
        first = rng.normal(0, np.sqrt(2 / self.features), (self.hidden, self.features + 1))
        second = rng.normal(0, np.sqrt(1 / self.hidden), (self.classes, self.hidden + 1))
        first[:, -1] = second[:, -1] = 0
        return np.concatenate([first.ravel(), second.ravel()])

    def _split(self, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        cut = self.hidden * (self.features + 1)
        return w[:cut].reshape(self.hidden, -1), w[cut:].reshape(self.classes, -1)

    def scores(self, w: np.ndarray, x: np.ndarray) -> np.ndarray:
        a, b = self._split(w)
        return np.maximum(x @ a[:, :-1].T + a[:, -1], 0) @ b[:, :-1].T + b[:, -1]

    def gradient(self, w: np.ndarray, x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, float]:
        a, b = self._split(w)
        h = np.maximum(x @ a[:, :-1].T + a[:, -1], 0)
        p, loss = _softmax(h @ b[:, :-1].T + b[:, -1], y)
        p[np.arange(len(y)), y] -= 1
        p /= len(y)
        back = (p @ b[:, :-1]) * (h > 0)
        return np.concatenate([np.column_stack([back.T @ x, back.sum(0)]).ravel(), np.column_stack([p.T @ h, p.sum(0)]).ravel()]), loss


@dataclass(frozen=True)
class Linear:
    """Least squares on dense rows."""

    features: int

    @property
    def size(self) -> int:
        return self.features + 1

    def start(self, seed: int) -> np.ndarray:
        return np.zeros(self.size)

    def scores(self, w: np.ndarray, x: np.ndarray) -> np.ndarray:
        return (x @ w[:-1] + w[-1])[:, None]

    def gradient(self, w: np.ndarray, x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, float]:
        off = self.scores(w, x)[:, 0] - y
        return np.append(off @ x, off.sum()) / len(y), float(0.5 * (off * off).mean())


def logistic(features: int) -> Softmax:
    """Two classes: logistic regression in its symmetric form."""
    return Softmax(features, 2)


def _softmax(scores: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, float]:
    scores = scores - scores.max(1, keepdims=True)
    p = np.exp(scores)
    p /= p.sum(1, keepdims=True)
    return p, float(-np.log(np.maximum(p[np.arange(len(y)), y], 1e-300)).mean())
