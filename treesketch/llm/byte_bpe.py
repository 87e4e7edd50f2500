"""Byte-level BPE through sentencepiece, with a model built from a rank file.

The vocabulary is written straight into a sentencepiece model: each token's
bytes become characters, one for a byte, and its score is its negative rank, so
that sentencepiece merges the pair of lowest rank first, as byte-level BPE
does. Texts are cut into pre-tokens by the vocabulary's pattern and each
pre-token is encoded alone. Decoding looks the ids' bytes up.
"""

from __future__ import annotations

import base64
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treesketch.llm.storage import only, small_batches
from treesketch.llm.wordpieces import text_groups
from treesketch.llm.worker import kept

#: A byte b is written as the character U+0100 + b.
BYTE_BASE = 0x100
#: Distinct pre-tokens whose ids a worker keeps (some 50 MB).
KEPT_PRETOKENS = 250_000


def default_ranks() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_multi_50k.tiktoken")


def default_pattern() -> str:
    import public_tokenizers

    return public_tokenizers.PATTERN


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as file:
        return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in file if line.strip())}


def _varint(n: int) -> bytes:
    out = bytearray()
    while n > 0x7F:
        out.append(n & 0x7F | 0x80)
        n >>= 7
    out.append(n)
    return bytes(out)


def _field(number: int, value: bytes | int | float) -> bytes:
    """One field of a protocol buffer: bytes, a varint or a 32-bit float."""
    if isinstance(value, bytes):
        return _varint(number << 3 | 2) + _varint(len(value)) + value
    if isinstance(value, float):
        return _varint(number << 3 | 5) + struct.pack("<f", value)
    return _varint(number << 3) + _varint(value)


def as_characters(raw: bytes) -> str:
    return "".join(chr(BYTE_BASE + b) for b in raw)


def sentencepiece_model(ranks: dict[bytes, int]) -> bytes:
    """A serialised sentencepiece BPE model whose ids are rank + 1 (0: unknown).

    Fixed values of the format: model 1 pieces, 2 trainer, 3 normaliser; piece
    1 text, 2 score, 3 type (1 normal, 2 unknown); trainer 3 type (2 BPE),
    4 size; normaliser 1 name, 3 dummy prefix, 4 extra spaces, 5 escapes.
    """
    ordered = sorted(ranks, key=ranks.get)
    if [ranks[t] for t in ordered] != list(range(len(ordered))):
        raise ValueError("ranks must be 0, 1, 2, ...")
    if missing := [b for b in range(256) if bytes([b]) not in ranks]:
        raise ValueError(f"the vocabulary lacks single bytes: {missing[:5]}")
    pieces = [_field(1, _field(1, b"<unk>") + _field(2, 0.0) + _field(3, 2))]
    pieces += [_field(1, _field(1, as_characters(t).encode()) + _field(2, -float(r)) + _field(3, 1)) for r, t in enumerate(ordered)]
    trainer = _field(2, _field(3, 2) + _field(4, len(pieces)))
    normaliser = _field(3, _field(1, b"identity") + _field(3, 0) + _field(4, 0) + _field(5, 0))
    return b"".join(pieces) + trainer + normaliser


class ByteBpe:
    """Encodes texts to ids as tiktoken does without special tokens; decodes ids to bytes."""

    def __init__(self, ranks_path: str, pattern: str, keep: int = KEPT_PRETOKENS):
        import regex
        import sentencepiece

        self.ranks = read_ranks(ranks_path)
        self.processor = sentencepiece.SentencePieceProcessor(model_proto=sentencepiece_model(self.ranks))
        self._cut = regex.compile(pattern).findall
        self._shift = {b: BYTE_BASE + b for b in range(256)}
        self._keep, self._known = keep, {"": b""}

    def encode(self, texts: list[str | None]) -> list[np.ndarray]:
        cut = [self._cut(t) if t else [] for t in texts]
        fresh: set[str] = set()
        for pretokens in cut:
            fresh.update(pretokens)
        new = self._encode_new([p for p in fresh if p not in self._known])
        if len(self._known) < self._keep:
            self._known.update(new)
        known = self._known.get
        return [np.frombuffer(b"".join([ids if (ids := known(p)) is not None else new[p] for p in pretokens]), "<u4") for pretokens in cut]

    def _encode_new(self, pretokens: list[str]) -> dict[str, bytes]:
        out, rest, mapped = {}, [], []
        for p in pretokens:
            raw = p.encode()
            if (rank := self.ranks.get(raw)) is not None:  # a whole token is never split
                out[p] = rank.to_bytes(4, "little")
            else:
                rest.append(p)
                mapped.append(raw.decode("latin-1").translate(self._shift))
        if rest:
            for p, ids in zip(rest, self.processor.encode(mapped, out_type=int, num_threads=1)):
                out[p] = (np.array(ids, "<u4") - np.uint32(1)).astype("<u4").tobytes()
        return out


def encode_byte_bpe(docs: DataFrame, *, ranks: str | None = None, pattern: str | None = None) -> DataFrame:
    """``doc_id, ids array<int>`` for each row of ``docs(doc_id, text)``; null texts are empty."""
    ranks, pattern = ranks or default_ranks(), pattern or default_pattern()
    small_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = kept(("byte bpe", ranks, pattern), lambda: ByteBpe(ranks, pattern))
        for batch in batches:
            texts = batch.column(1).to_pylist()
            for a, b in text_groups(texts):
                ids = coder.encode(texts[a:b])
                stops = np.cumsum([0] + [len(x) for x in ids]).astype(np.int32)
                flat = np.concatenate(ids) if ids else np.zeros(0, "<u4")
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.ListArray.from_arrays(pa.array(stops), pa.array(flat.astype(np.int32)))], names=["doc_id", "ids"])

    return only(docs, "doc_id", "text").select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, ids array<int>")


def decode_byte_bpe(encoded: DataFrame, *, ranks: str | None = None) -> DataFrame:
    """Adds ``decoded binary`` to rows of ``doc_id, ids``: the ids' bytes in a row."""
    ranks = ranks or default_ranks()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        inverse = read_ranks(ranks)
        table = sorted(inverse, key=inverse.get)
        for batch in batches:
            lists = batch.column(1)
            flat, at = lists.values.to_numpy(zero_copy_only=False), lists.offsets.to_numpy()
            decoded = [b"".join([table[i] for i in flat[a:b].tolist()]) for a, b in zip(at, at[1:])]
            yield pa.RecordBatch.from_arrays([batch.column(0), lists, pa.array(decoded, pa.binary())], names=["doc_id", "ids", "decoded"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, ids array<int>, decoded binary")
