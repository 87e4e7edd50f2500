"""Token-id output: concatenated ids with Elias-Fano document boundaries.

A token dataset is a Parquet folder of block rows. A block holds some
consecutive documents in ascending ``doc_id`` order: their ids in one array and
two Elias-Fano sequences, the boundaries within that array and the document
ids. Blocks of a shard are consecutive, shards ascend, so a document's place in
the whole output is its shard's base + its block's start + one select.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treesketch.llm.storage import only, small_batches
from treesketch.llm.wordpieces import WordPieceEncoder, default_path, text_groups
from treesketch.llm.worker import kept

#: Ids after which a block is closed; it always ends with a whole document.
BLOCK_TOKENS = 1 << 18
#: One position in so many ones of the upper bits is stored for select.
SELECT_STRIDE = 128

BLOCK_SCHEMA = (
    "shard int, block int, start long, n_docs int, n_null_ids int, n_tokens long, width int, "
    "ids binary, ends binary, doc_ids binary, id_base long, id_last long"
)
DOCUMENT_SCHEMA = "doc_id long, start long, n_tokens long, ids binary"


class EliasFano:
    """A non-decreasing sequence below ``universe`` in about 2 + log2(u/n) bits a value.

    Lower bits stand side by side; the upper bits are unary gaps. ``select(i)``
    finds the i-th one from the nearest stored position and a count of bits.
    """

    _HEAD = "<QQBI"

    def __init__(self, n: int, universe: int, low_bits: int, low: np.ndarray, high: np.ndarray, marks: np.ndarray):
        self.n, self.universe, self.low_bits = n, universe, low_bits
        self._low, self._high, self._marks = low, high, marks

    @classmethod
    def of(cls, values: np.ndarray, universe: int) -> EliasFano:
        values = np.asarray(values, np.uint64)
        n = len(values)
        if n and (int(values[-1]) > universe or np.any(values[1:] < values[:-1])):
            raise ValueError("values must not decrease and must stay within the universe")
        low_bits = max(0, (max(1, universe) // max(1, n)).bit_length() - 1)
        shifts = np.arange(low_bits, dtype=np.uint64)
        low = np.packbits(((values[:, None] >> shifts) & np.uint64(1)).astype(np.uint8), bitorder="little") if n and low_bits else np.zeros(0, np.uint8)
        ones = (values >> np.uint64(low_bits)).astype(np.int64) + np.arange(n)
        bits = np.zeros(int(ones[-1]) + 1 if n else 0, np.uint8)
        bits[ones] = 1
        return cls(n, universe, low_bits, low, np.packbits(bits, bitorder="little"), ones[::SELECT_STRIDE].astype("<u4"))

    def to_bytes(self) -> bytes:
        return struct.pack(self._HEAD, self.n, self.universe, self.low_bits, len(self._high)) + self._high.tobytes() + self._marks.tobytes() + self._low.tobytes()

    @classmethod
    def from_bytes(cls, raw: bytes) -> EliasFano:
        n, universe, low_bits, n_high = struct.unpack_from(cls._HEAD, raw)
        at, marks = struct.calcsize(cls._HEAD), -(-n // SELECT_STRIDE)
        high = np.frombuffer(raw, np.uint8, n_high, at)
        return cls(n, universe, low_bits, np.frombuffer(raw, np.uint8, -1, at + n_high + 4 * marks), high, np.frombuffer(raw, "<u4", marks, at + n_high))

    def _low_value(self, i: int) -> int:
        first = i * self.low_bits
        at, end = first >> 3, (first + self.low_bits + 7) >> 3
        return int.from_bytes(self._low[at:end].tobytes(), "little") >> (first & 7) & ((1 << self.low_bits) - 1)

    def select(self, i: int) -> int:
        """The i-th value (from 0), touching only the bits near its stored mark."""
        if not 0 <= i < self.n:
            raise IndexError(i)
        at, left = int(self._marks[i // SELECT_STRIDE]), i % SELECT_STRIDE
        byte = at >> 3
        word = int.from_bytes(self._high[byte : byte + 8].tobytes(), "little") >> (at & 7) << (at & 7)
        while left >= word.bit_count():
            left -= word.bit_count()
            byte += 8
            word = int.from_bytes(self._high[byte : byte + 8].tobytes(), "little")
        for _ in range(left):
            word &= word - 1
        place = (byte << 3) + (word & -word).bit_length() - 1
        return (place - i) << self.low_bits | self._low_value(i)

    def find(self, value: int) -> range:
        """The indices that hold ``value``, by binary searches over ``select``."""
        low, high = 0, self.n
        while low < high:
            middle = (low + high) // 2
            low, high = (middle + 1, high) if self.select(middle) < value else (low, middle)
        end = low
        while end < self.n and self.select(end) == value:
            end += 1
        return range(low, end)

    def values(self) -> np.ndarray:
        """All values: what ``select`` gives for each i, in one pass."""
        ones = np.flatnonzero(np.unpackbits(self._high, bitorder="little"))[: self.n]
        out = (ones - np.arange(self.n)).astype(np.uint64) << np.uint64(self.low_bits)
        if self.low_bits and self.n:
            bits = np.unpackbits(self._low, count=self.n * self.low_bits, bitorder="little").reshape(self.n, self.low_bits)
            out |= (bits.astype(np.uint64) << np.arange(self.low_bits, dtype=np.uint64)).sum(1, dtype=np.uint64)
        return out.astype(np.int64)


def _block(shard: int, block: int, start: int, doc_ids: list[int | None], parts: list[bytes], width: int) -> dict:
    ends = np.cumsum([len(p) // width for p in parts], dtype=np.int64)
    known = np.array([d for d in doc_ids if d is not None], np.int64)
    base = int(known[0]) if len(known) else 0
    span = known.astype(np.uint64) - np.uint64(base & 0xFFFFFFFFFFFFFFFF)
    return {
        "shard": shard, "block": block, "start": start, "n_docs": len(parts), "n_null_ids": len(doc_ids) - len(known),
        "n_tokens": int(ends[-1]), "width": width, "ids": b"".join(parts), "ends": EliasFano.of(ends, int(ends[-1])).to_bytes(),
        "doc_ids": EliasFano.of(span, int(span[-1]) if len(span) else 0).to_bytes(), "id_base": base, "id_last": int(known[-1]) if len(known) else None,
    }


def write_token_dataset(
    docs: DataFrame, path: str, *, tokenizer: str | None = None, end_id: int = 2, shards: int | None = None, block_tokens: int = BLOCK_TOKENS
) -> str:
    """Encode ``docs(doc_id, text)`` and write a token dataset at ``path``.

    Every document counts, in ascending ``doc_id`` order (null ids first, equal
    ids in the order of their texts' hashes); a null or empty text has only the
    end id. One range shuffle of the texts, which spreads equal ids by hash;
    the encoder runs after it, so the sampling pass does not encode.
    """
    spark = docs.sparkSession
    tokenizer = tokenizer or default_path()
    small_batches(spark)
    shards = shards or int(spark.conf.get("spark.sql.shuffle.partitions"))

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encoder = kept(("word pieces", tokenizer), lambda: WordPieceEncoder(tokenizer))
        width = encoder.dtype.itemsize
        end = np.array([end_id], encoder.dtype).tobytes()
        shard, block, start, held = TaskContext.get().partitionId(), 0, 0, 0
        doc_ids, parts = [], []

        def close() -> pa.RecordBatch:
            return pa.RecordBatch.from_pylist([_block(shard, block, start, doc_ids, parts, width)], schema=arrow)

        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for a, b in text_groups(texts):
                for doc_id, raw in zip(ids[a:b], encoder.encode(texts[a:b])):
                    doc_ids.append(doc_id)
                    parts.append(raw + end)
                    held += len(parts[-1]) // width
                    if held >= block_tokens:
                        yield close()
                        block, start, held, doc_ids, parts = block + 1, start + held, 0, [], []
        if parts:
            yield close()

    arrow = pa.schema([
        ("shard", pa.int32()), ("block", pa.int32()), ("start", pa.int64()), ("n_docs", pa.int32()), ("n_null_ids", pa.int32()), ("n_tokens", pa.int64()),
        ("width", pa.int32()), ("ids", pa.binary()), ("ends", pa.binary()), ("doc_ids", pa.binary()), ("id_base", pa.int64()), ("id_last", pa.int64()),
    ])
    order = [F.col("doc_id").asc_nulls_first(), F.xxhash64("text")]
    ranged = only(docs, "doc_id", "text").select(F.col("doc_id").cast("long").alias("doc_id"), "text").repartitionByRange(shards, *order).sortWithinPartitions(*order)
    ranged.mapInArrow(blocks, BLOCK_SCHEMA).write.parquet(path)
    return path


def _bases(blocks: DataFrame) -> dict[int, int]:
    """Ids before each shard; the shards' totals, one number for each writing task, are all that comes to the driver."""
    bases, total = {}, 0
    for row in blocks.groupBy("shard").agg(F.sum("n_tokens").alias("n")).orderBy("shard").collect():
        bases[row["shard"]], total = total, total + row["n"]
    return bases


class Block:
    """One block row: documents are found by ``select`` on its two sequences."""

    def __init__(self, row: dict, base: int):
        self.ends, self.names = EliasFano.from_bytes(row["ends"]), EliasFano.from_bytes(row["doc_ids"])
        self.nulls, self.id_base, self.start = row["n_null_ids"], row["id_base"], base + row["start"]
        self.ids = np.frombuffer(row["ids"], "<u2" if row["width"] == 2 else "<u4")

    def bounds(self, i: int) -> tuple[int, int]:
        return self.ends.select(i - 1) if i else 0, self.ends.select(i)

    def named(self, doc_id: int) -> range:
        """Indices of the documents of that id."""
        found = self.names.find(doc_id - self.id_base) if doc_id >= self.id_base else range(0)
        return range(found.start + self.nulls, found.stop + self.nulls)


def _documents(blocks: DataFrame, bases: dict[int, int], only: int | None) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                block = Block(row, bases[row["shard"]])
                chosen = range(block.ends.n) if only is None else block.named(only)
                if not len(chosen):
                    continue
                bounds = [block.bounds(i) for i in chosen[:1]]
                for i in chosen[1:]:  # neighbours share a boundary
                    bounds.append((bounds[-1][1], block.ends.select(i)))
                cuts = np.array([bounds[0][0], *[b for _, b in bounds]], np.int64)
                ids = block.ids[cuts[0] : cuts[-1]].astype("<u4")
                data = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(chosen), [None, pa.py_buffer((cuts - cuts[0]) * 4), pa.py_buffer(ids)])
                names = [None if i < block.nulls else block.id_base + block.names.select(i - block.nulls) for i in chosen]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(names, pa.int64()), pa.array(cuts[:-1] + block.start), pa.array(np.diff(cuts)), data.cast(pa.binary())],
                    names=["doc_id", "start", "n_tokens", "ids"],
                )

    return blocks.select("shard", "start", "n_null_ids", "width", "ids", "ends", "doc_ids", "id_base").mapInArrow(run, DOCUMENT_SCHEMA)


def read_token_dataset(spark: SparkSession, path: str) -> DataFrame:
    """Documents of a token dataset: ``doc_id, start, n_tokens, ids``.

    ``start`` counts the ids of all documents before it; ``ids`` are
    little-endian unsigned 32-bit integers. Boundaries and document ids come
    from ``select``; no table of offsets is kept.
    """
    blocks = spark.read.schema(BLOCK_SCHEMA).parquet(path)
    return _documents(blocks, _bases(blocks), None)


def read_document(spark: SparkSession, path: str, doc_id: int) -> DataFrame:
    """The rows of one document, as ``read_token_dataset`` has them; none if there is no such id.

    Blocks are pruned by the least and greatest id that the Parquet files
    record; in a block the id is found by binary search, its ids by two selects.
    """
    blocks = spark.read.schema(BLOCK_SCHEMA).parquet(path)
    near = blocks.where((F.col("id_base") <= doc_id) & (F.col("id_last") >= doc_id))
    return _documents(near, _bases(blocks), doc_id)
