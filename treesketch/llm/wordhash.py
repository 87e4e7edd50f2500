"""Hashes of words and word shingles, vectorised over a text's bytes.

Words are ``[^\\x20\\x09-\\x0D]+`` with A-Z lower-cased. A word's 64-bit hash is
a polynomial over random values of its bytes, taken from prefix sums, so no
word becomes a Python object.
"""

from __future__ import annotations

import numpy as np

#: Bytes hashed at a time, cut at white space; bounds the temporary arrays.
WINDOW = 1 << 20


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijection that spreads every input bit (multiply and shift twice)."""
    x = np.asarray(x, np.uint64)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def odd_constants(n: int, seed: int) -> np.ndarray:
    return mix64(np.arange(1, n + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed)) | np.uint64(1)


class WordHasher:
    def __init__(self, fold_case: bool = True):
        fold = np.arange(256, dtype=np.uint8)
        if fold_case:
            fold[65:91] += 32
        self._values = odd_constants(256, 11)[fold]
        self._space = np.zeros(256, bool)
        self._space[[0x20, 9, 10, 11, 12, 13]] = True
        self._size = 0
        self._grow(1 << 12)

    def _grow(self, n: int) -> None:
        while self._size < n:
            self._size = max(1 << 12, 2 * self._size)
        base, inverse = 0x9E3779B97F4A7C15 | 1, pow(0x9E3779B97F4A7C15 | 1, -1, 1 << 64)
        self._powers, self._inverses = (np.multiply.accumulate(np.concatenate([[np.uint64(1)], np.full(self._size, b, np.uint64)])) for b in (np.uint64(base), np.uint64(inverse)))

    def spans(self, raw: bytes) -> tuple[np.ndarray, np.ndarray]:
        """Start and end of each word, in bytes."""
        space = np.ones(len(raw) + 2, bool)
        space[1:-1] = self._space[np.frombuffer(raw, np.uint8)]
        edges = np.flatnonzero(space[1:] != space[:-1])
        return edges[0::2], edges[1::2]

    def words(self, raw: bytes) -> np.ndarray:
        """One hash for each word, in order."""
        if len(raw) <= WINDOW:
            return self._words(raw)
        out, at = [], 0
        while at < len(raw):
            stop = at + WINDOW
            if stop < len(raw):
                cut = max(raw.rfind(b" ", at, stop), raw.rfind(b"\n", at, stop))
                if cut < 0:  # a very long word: take it whole
                    ends = [i for i in (raw.find(b" ", stop), raw.find(b"\n", stop)) if i >= 0]
                    cut = min(ends, default=len(raw) - 1)
                stop = cut + 1
            out.append(self._words(raw[at:stop]))
            at = stop
        return np.concatenate(out) if out else np.zeros(0, np.uint64)

    def _words(self, raw: bytes) -> np.ndarray:
        if not raw:
            return np.zeros(0, np.uint64)
        if len(raw) > self._size:
            self._grow(len(raw))
        start, end = self.spans(raw)
        if not len(start):
            return np.zeros(0, np.uint64)
        values = self._values[np.frombuffer(raw, np.uint8)] * self._powers[: len(raw)]
        sums = np.concatenate([[np.uint64(0)], np.cumsum(values, dtype=np.uint64)])
        return mix64((sums[end] - sums[start]) * self._inverses[start] + (end - start).astype(np.uint64))


def shingle_hashes(words: np.ndarray, size: int) -> np.ndarray:
    """Hashes of all runs of ``size`` words; of the whole sequence, if it is shorter and not empty."""
    if not len(words):
        return words
    width = min(size, len(words))
    constants, n = odd_constants(size, 23), len(words) - width + 1
    out = np.full(n, np.uint64(width))
    for j in range(width):
        out = out + words[j : j + n] * constants[j]
    return mix64(out)
