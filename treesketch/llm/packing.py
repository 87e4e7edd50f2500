"""Sum-of-squares packing of token pieces into sequences of one length.

Each piece goes where the sum, over residual gaps, of the squared number of
open sequences with that gap becomes smallest: gaps that few sequences have are
filled last, so the open gaps stay varied and later pieces find exact fits.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treesketch.llm.storage import materialize, only, small_batches
from treesketch.llm.wordpieces import WordPieceEncoder, default_path, text_groups
from treesketch.llm.worker import kept

#: Pieces that one task packs on average. Each task leaves a few part-filled sequences.
PIECES_PER_TASK = 100_000


def sum_of_squares_pack(lengths: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Sequence number and offset of each piece; lengths lie in 1..capacity.

    Longest first, so that short pieces are left for the small gaps. A new
    sequence is opened only when no open one has room: weighed by the rule as
    one more gap it would be opened too soon, which cost 36 sequences more than
    the least possible 11,756 on 53,782 pieces; without it there were none.
    """
    lengths = np.asarray(lengths, np.int64)
    order = np.argsort(-lengths, kind="stable")
    sequence, offset = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64)
    count = np.zeros(capacity + 1, np.int64)  # open sequences by gap; a gap of 0 is closed and not counted
    stacks: list[list[int]] = [[] for _ in range(capacity + 1)]
    opened = 0
    for i in order.tolist():
        size = int(lengths[i])
        if size < 1 or size > capacity:
            raise ValueError(f"a piece of {size} does not fit {capacity}")
        # change of the sum for a gap g = r + size that becomes r: 2 * (count[r] - count[g]) + 2, or 1 - 2 * count[g] where r = 0
        before = count[size:]
        change = 2 * (count[: len(before)] - before) + 2
        change[0] = 1 - 2 * before[0]
        change[before == 0] = np.iinfo(np.int64).max
        left = int(np.argmin(change))
        if change[left] == np.iinfo(np.int64).max:
            bin_, gap = opened, capacity
            opened += 1
        else:
            gap = left + size
            bin_ = stacks[gap].pop()
            count[gap] -= 1
        sequence[i], offset[i] = bin_, capacity - gap
        if gap > size:
            stacks[gap - size].append(bin_)
            count[gap - size] += 1
    return sequence, offset


def token_pieces(docs: DataFrame, *, tokenizer: str | None = None, end_id: int = 1, capacity: int = 4096) -> DataFrame:
    """``doc_id, piece, start, length, ids``: documents' ids with the end id, cut after each ``capacity``.

    A null or empty text is the end id alone. ``ids`` are little-endian
    unsigned 32-bit integers.
    """
    tokenizer = tokenizer or default_path()
    small_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = kept(("word pieces", tokenizer), lambda: WordPieceEncoder(tokenizer))
        end = np.array([end_id], "<u4").tobytes()
        for batch in batches:
            doc_ids, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for a, b in text_groups(texts):
                rows = []
                for doc_id, raw in zip(doc_ids[a:b], encoder.encode(texts[a:b])):
                    ids = np.frombuffer(raw, encoder.dtype).astype("<u4").tobytes() + end
                    for piece, at in enumerate(range(0, len(ids), 4 * capacity)):
                        cut = ids[at : at + 4 * capacity]
                        rows.append((doc_id, piece, at // 4, len(cut) // 4, cut))
                columns = list(zip(*rows))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.binary()))], names=["doc_id", "piece", "start", "length", "ids"])

    return only(docs, "doc_id", "text").select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, piece int, start long, length long, ids binary")


def pack_pieces(pieces: DataFrame, *, capacity: int = 4096, pieces_per_task: int = PIECES_PER_TASK) -> DataFrame:
    """Adds ``sequence_id, offset`` to rows that have ``length``; other columns pass through.

    The rows are written once, for their number sets that of the packing tasks,
    and dealt evenly whatever their values. Sequences of different tasks have
    different ids (task number in the upper 31 bits); ids need not be dense.
    """
    rows = materialize(pieces, "pieces")
    tasks = max(1, -(-rows.count() // pieces_per_task))
    names, schema = rows.columns, rows.schema.simpleString()[len("struct<") : -1].replace(":", " ")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        held = [b for b in batches if b.num_rows]
        if not held:
            return
        table = pa.Table.from_batches(held)
        sequence, offset = sum_of_squares_pack(table.column("length").to_numpy(), capacity)
        first = TaskContext.get().partitionId() << 32
        yield from table.append_column("sequence_id", pa.array(sequence + first)).append_column("offset", pa.array(offset)).to_batches(max_chunksize=10_000)

    return rows.select(*names).repartition(tasks).mapInArrow(run, f"{schema}, sequence_id long, offset long")
