"""From raw documents to packed training sequences, a stage at a time.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; ``run`` writes
it as Parquet in the shared folder and rereads it as the next stage's docs. All
stages but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treesketch.llm.factorization import fit_quality, score_quality
from treesketch.llm.line_dedup import drop_lines, keep_bitmaps
from treesketch.llm.near_dedup import near_duplicates
from treesketch.llm.packing import pack_pieces, token_pieces
from treesketch.llm.passages import remove_repeats
from treesketch.llm.queries import GOOD
from treesketch.llm.storage import materialize, named_in, only, release_scratch, written

#: A document of which the line stage would leave less than this share of its characters is a copy among ten and stays whole for the near-duplicate stage.
LEAST_LEFT = 0.5

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _like_documents(docs: DataFrame) -> DataFrame:
    return docs.select(*COLUMNS[:-1], F.coalesce(F.length("text"), F.lit(0)).cast("long").alias("n_chars"))


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose quality score is ``GOOD`` at least; the model is fitted on the given labels."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", F.col("quality").alias("label"))
    docs = only(docs, *COLUMNS)
    return score_quality(docs, fit_quality(docs, labels)).where(F.col("score") >= GOOD).select(*COLUMNS)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the lines that ten of them have; a document that is mostly such lines stays whole."""
    docs = only(docs, *COLUMNS)
    return _like_documents(drop_lines(docs, keep_bitmaps(docs, min_docs=10), least_left=LEAST_LEFT))


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates; documents without words or id are groups of their own.

    Rows that repeat a doc_id are one document: each of its different texts
    stays, once, with the least of its other columns, or all of them go.
    """
    docs = only(docs, *COLUMNS)
    groups = materialize(near_duplicates(docs), "groups").where(F.col("doc_id").isNotNull())
    kept = named_in(docs, groups.where("kept").select(F.col("doc_id").alias("id")).distinct(), "doc_id")
    twice = materialize(groups.groupBy(F.col("doc_id").alias("id")).agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("id"), "repeated")
    if not twice.isEmpty():
        rest = F.struct(*COLUMNS[2:])
        once = named_in(kept, twice, "doc_id").groupBy("doc_id", "text").agg(F.min(rest).alias("rest")).select("doc_id", "text", "rest.*")
        kept = named_in(kept, twice, "doc_id", "left_anti").unionByName(once)
    return kept.unionByName(docs.where(F.col("doc_id").isNull()))


def passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without passages of fifty words or more that an earlier document has."""
    return _like_documents(remove_repeats(only(docs, *COLUMNS)))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces placed in sequences of 4096: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    pieces = token_pieces(only(docs, *COLUMNS), end_id=1, capacity=4096)
    return pack_pieces(pieces.select("doc_id", "piece", "start", "length", F.crc32("ids").alias("ids_crc32")), capacity=4096)


STAGES = [("quality classifier", quality), ("line dedup", lines), ("minhash near-dedup", near), ("substring dedup", passages), ("best-fit packing", packing)]

#: Models, signatures and alignments are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order, each written and read again; the tables that a stage wrote on its way are deleted once its result stands."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        before = written()
        docs = materialize(stage(spark, docs, sf_dir), f"stage-{name.replace(' ', '-')}", whole=True)
        release_scratch(spark, before, keep=1)
    return docs
