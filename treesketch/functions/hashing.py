"""Signed-bucket hashing: one family as Spark columns, SQL text and NumPy.

With the prime p = 2^31 - 1, row r sends coordinate i to bucket
((a i + b) mod p) mod width (pairwise independent) with the sign
1 - 2 (q(i) mod p mod 2) of a cubic q (four-wise independent). All values stay
below 2^62, so BIGINT never overflows under ANSI rules.
"""

from __future__ import annotations

import json
import math
from dataclasses import asdict, dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: The modulus of all hashes.
PRIME = (1 << 31) - 1


def _draws(seed: int, row: int, n: int) -> list[int]:
    """``n`` integers in [1, PRIME - 1] from a multiplicative recurrence."""
    state = (seed * 1_000_003 + row * 7_919 + 12_345) % PRIME or 1
    out = []
    for _ in range(n + 8):
        state = (state * 48_271 + 11) % PRIME or 1
        out.append(state)
    return [max(1, x) for x in out[8:]]


@dataclass(frozen=True)
class SketchSpec:
    """Shape and seed of a signed-bucket sketch; ``rows`` is odd so that the median is one of them."""

    rows: int = 5
    width: int = 256
    seed: int = 7

    def __post_init__(self):
        if self.rows < 1 or self.rows % 2 == 0:
            raise ValueError("rows must be odd and positive")
        if not 1 <= self.width < PRIME:
            raise ValueError("width must lie in 1 .. 2^31 - 2")

    @property
    def size(self) -> int:
        return self.rows * self.width

    def coefficients(self, row: int) -> tuple[int, int, int, int, int, int]:
        """a, b of the bucket and c3, c2, c1, c0 of the sign."""
        return tuple(_draws(self.seed, row, 6))

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    @classmethod
    def from_json(cls, text: str) -> SketchSpec:
        return cls(**json.loads(text))

    # Spark columns
    def bucket(self, coord: Column, row: int) -> Column:
        a, b = self.coefficients(row)[:2]
        return ((coord * F.lit(a).cast("long") + F.lit(b).cast("long")) % F.lit(PRIME).cast("long") % self.width).cast("int")

    def sign(self, coord: Column, row: int) -> Column:
        p = F.lit(PRIME).cast("long")
        c3, c2, c1, c0 = (F.lit(c).cast("long") for c in self.coefficients(row)[2:])
        cubic = (((c3 * coord + c2) % p * coord + c1) % p * coord + c0) % p
        return F.lit(1).cast("long") - F.lit(2).cast("long") * (cubic % 2)

    # SQL text that Spark and DuckDB both take
    def sql_rows(self, name: str = "hash_rows") -> str:
        """A common table expression with a line of coefficients for each row."""
        values = ", ".join(f"({r}, {', '.join(f'CAST({c} AS BIGINT)' for c in self.coefficients(r))})" for r in range(self.rows))
        return f"{name} AS (SELECT * FROM (VALUES {values}) AS t(hrow, a, b, c3, c2, c1, c0))"

    def sql_bucket(self, coord: str) -> str:
        return f"CAST(((a * {coord} + b) % {PRIME}) % {self.width} AS INT)"

    def sql_sign(self, coord: str) -> str:
        return f"(1 - 2 * ((((((c3 * {coord} + c2) % {PRIME}) * {coord} + c1) % {PRIME}) * {coord} + c0) % {PRIME} % 2))"

    # NumPy
    def np_buckets(self, coord: np.ndarray) -> np.ndarray:
        i = np.asarray(coord, np.int64)
        return np.stack([(a * i + b) % PRIME % self.width for a, b, *_ in map(self.coefficients, range(self.rows))])

    def np_signs(self, coord: np.ndarray) -> np.ndarray:
        i = np.asarray(coord, np.int64)
        out = []
        for _, _, c3, c2, c1, c0 in map(self.coefficients, range(self.rows)):
            out.append(1 - 2 * ((((c3 * i + c2) % PRIME * i + c1) % PRIME * i + c0) % PRIME % 2))
        return np.stack(out)


def size_for(d: int, eps: float, alpha: float = 1.0, delta: float = 0.05, *, seed: int = 7, form: str = "inverse_square") -> SketchSpec:
    """Rows and width from accuracy ``eps``, heaviness ``alpha``, failure ``delta`` and dimension ``d``.

    Rows are the odd number at or above log2(d / delta); the width is
    1 / (eps alpha)^2, or 1 / eps with ``form="inverse_eps"``.
    """
    if d < 1 or not 0 < eps <= 1 or not 0 < alpha <= 1 or not 0 < delta < 1:
        raise ValueError("d >= 1 and eps, alpha, delta in (0, 1] are needed")
    rows = math.ceil(math.log2(d / delta)) | 1
    if form == "inverse_square":
        width = math.ceil(1 / (eps * alpha) ** 2)
    elif form == "inverse_eps":
        width = math.ceil(1 / eps)
    else:
        raise ValueError("form is 'inverse_square' or 'inverse_eps'")
    return SketchSpec(rows, max(1, width), seed)


def fold_domain(key: Column, seed: int = 0) -> Column:
    """A coordinate below the prime for keys beyond it; n keys collide with about n^2 / 2^32 pairs."""
    return F.pmod(F.xxhash64(F.lit(seed), key), F.lit(PRIME).cast("long"))


def fill_coefficients(seed: int, step: int) -> tuple[int, int, int]:
    a, b, c = _draws(seed * 31 + 17, step, 3)
    return a, b, c


def fill_order(coord: Column, seed: int, step: int) -> Column:
    """A shared pseudo-random rank of a coordinate: equal wherever it is computed."""
    a, b, c = (F.lit(x).cast("long") for x in fill_coefficients(seed, step))
    p = F.lit(PRIME).cast("long")
    return (coord * a + b) % p * c % p


def sql_fill_order(coord: str, seed: int, step: int) -> str:
    a, b, c = fill_coefficients(seed, step)
    return f"((({coord} * CAST({a} AS BIGINT) + {b}) % {PRIME}) * CAST({c} AS BIGINT)) % {PRIME}"


def np_fill_order(coord: np.ndarray, seed: int, step: int) -> np.ndarray:
    a, b, c = fill_coefficients(seed, step)
    return (np.asarray(coord, np.int64) * a + b) % PRIME * c % PRIME
