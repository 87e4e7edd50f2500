"""Exact line deduplication, in DataFrame functions only.

Line keys are hashed to 128 bits. The hashes are range-partitioned together
with their document and sorted by hash, document and position, so a frequent
line is split over tasks and each task streams its runs; what a run gives, a
count of documents and the first occurrence, is merged per key. The result is a
bitmap for each document, not text: 64 lines to a word, words without a dropped
line left out.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from treesketch.llm.storage import Columns, materialize, only

#: White space stripped from a line's ends, and the letters that are lower-cased (fixed values).
STRIPPED = "\x20\x09\x0a\x0b\x0c\x0d"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Keys (40 bytes each) that may be broadcast; more of them are joined by a shuffle.
BROADCAST_KEYS = 500_000


def _rows(docs: DataFrame) -> DataFrame:
    """``dk, th, text``: what a row is known by. A row without doc_id is its own document."""
    text = F.coalesce(F.col("text"), F.lit(""))
    th = F.xxhash64(text)
    return only(docs, "doc_id", "text").select(F.coalesce(F.col("doc_id").cast("long"), th).alias("dk"), th.alias("th"), text.alias("text"), F.col("doc_id").cast("long").alias("doc_id"))


def line_hashes(docs: DataFrame, min_chars: int = 1) -> DataFrame:
    """``dk, th, pos, h1, h2`` for each line whose key has ``min_chars`` code points at least."""
    lines = F.split(F.translate("text", UPPER, LOWER), "\n", -1)
    key = F.trim(F.col("line"), F.lit(STRIPPED))
    exploded = _rows(docs).select("dk", "th", F.posexplode(lines).alias("pos", "line")).select("dk", "th", "pos", key.alias("key"))
    return exploded.where(F.length("key") >= min_chars).select("dk", "th", "pos", F.xxhash64("key").alias("h1"), F.xxhash64(F.lit(7), "key").alias("h2"))


def frequent_keys(hashes: DataFrame, min_docs: int) -> DataFrame:
    """``h1, h2, n_docs, first`` of keys in ``min_docs`` documents at least; ``first`` is the least (dk, pos)."""
    tasks = int(hashes.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = hashes.select("h1", "h2", "dk", "pos").repartitionByRange(tasks, "h1", "h2", "dk").sortWithinPartitions("h1", "h2", "dk", "pos")
    runs = ranged.groupBy("h1", "h2", "dk").agg(F.min("pos").alias("pos"))
    return runs.groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("n_docs"), F.min(F.struct("dk", "pos")).alias("first")).where(F.col("n_docs") >= min_docs)


def keep_bitmaps(docs: DataFrame, *, min_docs: int = 10, min_chars: int = 1, keep: str = "none") -> DataFrame:
    """``dk, th, dropped map<int, bigint>, n_dropped`` for documents that lose a line.

    ``keep="none"``: keys in ``min_docs`` documents lose all their lines.
    ``keep="first"``: they keep the first occurrence in the order (doc_id,
    position). A line at position p is dropped if bit p % 64 of word p div 64
    is set; absent words and documents keep all their lines.
    """
    if keep not in ("none", "first"):
        raise ValueError("keep is 'none' or 'first'")
    hashes = materialize(line_hashes(docs, min_chars), "lines", whole=True)
    keys = materialize(frequent_keys(hashes, min_docs), "line-keys")
    small = keys if keep == "first" else keys.select("h1", "h2")
    if keys.count() <= BROADCAST_KEYS:
        small = F.broadcast(small)
    dropped = hashes.join(small, ["h1", "h2"])
    if keep == "first":
        dropped = dropped.where((F.col("dk") != F.col("first.dk")) | (F.col("pos") != F.col("first.pos")))
    word, bit = F.floor(F.col("pos") / 64).cast("int"), F.expr("shiftleft(1L, pos % 64)")
    words = dropped.select("dk", "th", word.alias("word"), bit.alias("bit")).groupBy("dk", "th", "word").agg(F.bit_or("bit").alias("bits"))
    return words.groupBy("dk", "th").agg(F.map_from_entries(F.collect_list(F.struct("word", "bits"))).alias("dropped"), F.sum(F.bit_count("bits")).cast("long").alias("n_dropped"))


def kept_lines(lines: Column, dropped: Column) -> Column:
    """The lines of an array that a ``dropped`` map leaves."""

    def stays(_: Column, i: Column) -> Column:
        word = F.element_at(dropped, F.floor(i / 64).cast("int"))
        return F.coalesce(F.getbit(word, i % 64) == 0, F.lit(True))

    return F.when(dropped.isNull(), lines).otherwise(F.filter(lines, stays))


def drop_lines(docs: DataFrame, bitmaps: DataFrame, *, least_left: float = 0.0) -> DataFrame:
    """``docs`` with ``text`` rebuilt from the lines its bitmap keeps, and ``n_lines, n_dropped``.

    A document of which less than the share ``least_left`` of its characters
    would be left keeps all its lines. Works on whole rows; given columns
    ``n_lines`` and ``n_dropped``, in any case, make way for the new ones, all
    others pass through, whatever their names.
    """
    given = Columns(docs)
    text = F.coalesce(F.col(given["text"]), F.lit(""))
    th = F.xxhash64(text)
    rows = given.frame.select("*", th.alias("th"), F.coalesce(F.col(given["doc_id"]).cast("long"), th).alias("dk"))
    joined = rows.join(bitmaps.select("dk", "th", "dropped", F.col("n_dropped").alias("n")), ["dk", "th"], "left")
    lines = F.split(text, "\n", -1)
    kept = F.when(F.col("dropped").isNull(), text).otherwise(F.array_join(kept_lines(lines, F.col("dropped")), "\n"))
    n_dropped = F.coalesce("n", F.lit(0))
    if least_left > 0:
        whole = F.length(kept) < least_left * F.length(text)
        kept, n_dropped = F.when(whole, text).otherwise(kept), F.when(whole, F.lit(0)).otherwise(n_dropped)
    places = [i for i in given.others(("n_lines", "n_dropped")) if i != given.place("text")]
    chosen = joined.select(*[f"_{i}" for i in places], kept.alias("text"), F.size(lines).cast("long").alias("n_lines"), n_dropped.cast("long").alias("n_dropped"))
    return given.named(chosen, places, ("text", "n_lines", "n_dropped"))
