"""Queries over the given tables for each operator of this subpackage, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _read(spark: SparkSession, sf_dir: str, table: str, *columns: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet").select(*columns)


def op1_prefix_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treesketch.llm.prefix_forest import nearest_neighbours

    vectors = _read(spark, sf_dir, "embeddings", "vec_id", "embedding")
    return nearest_neighbours(vectors, vectors.where(F.col("vec_id") % 20 == 0), k=20)


#: A document is held out where the CRC-32 of its id as text leaves this remainder.
HELD_OUT, FOLDS = 2, 4
#: Scores from here on count as good.
GOOD = 0.7


def op2_factorization_machine(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treesketch.llm.factorization import fit_quality, score_quality

    docs = _read(spark, sf_dir, "documents", "doc_id", "text")
    labels = _read(spark, sf_dir, "labels", "doc_id", F.col("quality").alias("label"))
    held_out = F.crc32(F.col("doc_id").cast("string")) % FOLDS == HELD_OUT
    scored = score_quality(docs, fit_quality(docs, labels))
    return scored.select("doc_id", F.coalesce(held_out, F.lit(False)).alias("held_out"), "score", (F.col("score") >= GOOD).cast("int").alias("predicted"))


def op3_passage_chains(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treesketch.llm.passages import remove_repeats

    out = remove_repeats(_read(spark, sf_dir, "documents", "doc_id", "text"))
    return out.select("doc_id", "n_words", "n_removed", F.size("spans").cast("long").alias("n_spans"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def op4_token_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treesketch.llm.storage import scratch_path
    from treesketch.llm.token_shards import read_token_dataset, write_token_dataset

    path = write_token_dataset(_read(spark, sf_dir, "documents", "doc_id", "text"), scratch_path(spark, "tokens"), end_id=2)
    return read_token_dataset(spark, path).select("doc_id", "start", "n_tokens", F.crc32("ids").alias("ids_crc32"))


def op5_minhash_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treesketch.llm.near_dedup import near_duplicates

    return near_duplicates(_read(spark, sf_dir, "documents", "doc_id", "text"), size=5, percent=75)


def op6_sum_of_squares_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treesketch.llm.packing import pack_pieces, token_pieces

    pieces = token_pieces(_read(spark, sf_dir, "documents", "doc_id", "text"), end_id=1, capacity=4096)
    digests = pieces.select("doc_id", "piece", "start", "length", F.crc32("ids").alias("ids_crc32"))
    return pack_pieces(digests, capacity=4096)


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treesketch.llm.line_dedup import drop_lines, keep_bitmaps

    docs = _read(spark, sf_dir, "documents", "doc_id", "text")
    out = drop_lines(docs, keep_bitmaps(docs, min_docs=10, min_chars=1))
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2("text", 256).alias("kept_sha256"))


def op8_tag_path_ratios(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treesketch.llm.html_text import extract_main_text

    texts = extract_main_text(_read(spark, sf_dir, "pages", "page_id", "url", "html"))
    return texts.withColumn("n_chars", F.length("text").cast("long"))


def op9_small_world(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treesketch.llm.hnsw import near_duplicate_vectors

    return near_duplicate_vectors(_read(spark, sf_dir, "embeddings", "vec_id", "embedding"), threshold=0.95)


def op10_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treesketch.llm.byte_bpe import decode_byte_bpe, encode_byte_bpe

    decoded = decode_byte_bpe(encode_byte_bpe(_read(spark, sf_dir, "documents", "doc_id", "text")))
    return decoded.select("doc_id", F.size("ids").cast("long").alias("n_tokens"), F.sha2(F.array_join("ids", ","), 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


_OP7_SQL = """
WITH lines AS (
  SELECT doc_id, i AS pos, parts[i] AS line FROM (
    SELECT doc_id, parts, unnest(range(1, len(parts) + 1)) AS i
    FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS parts FROM documents))
), keyed AS (
  SELECT *, translate(regexp_replace(line, '^[\\x20\\x09-\\x0D]+|[\\x20\\x09-\\x0D]+$', '', 'g'),
                      'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k FROM lines
), often AS (
  SELECT k FROM keyed WHERE length(k) >= 1 GROUP BY k HAVING count(DISTINCT doc_id) >= 10
)
SELECT doc_id, count(*) AS n_lines, count(o.k) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE o.k IS NULL), '')) AS kept_sha256
FROM keyed LEFT JOIN often o ON keyed.k = o.k GROUP BY doc_id
"""


_OP5_SQL = """
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents
), shingles AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) >= 5 THEN list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) ELSE [array_to_string(w, ' ')] END) AS s FROM words WHERE len(w) > 0
), sizes AS (
  SELECT d.doc_id, count(s.s) AS n FROM documents d LEFT JOIN shingles s ON s.doc_id = d.doc_id GROUP BY d.doc_id
), shared AS (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM shingles a JOIN shingles b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY ALL
), links AS (
  SELECT a, b FROM shared JOIN sizes x ON x.doc_id = a JOIN sizes y ON y.doc_id = b WHERE 100 * c >= 75 * (x.n + y.n - c)
), reach AS (
  SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, l.b FROM reach r JOIN links l ON l.a = r.b
)
SELECT s.doc_id, s.n AS n_shingles, min(r.b) AS component_id, min(r.b) = s.doc_id AS kept FROM sizes s JOIN reach r ON r.a = s.doc_id GROUP BY s.doc_id, s.n
"""

_OP9_SQL = """
WITH RECURSIVE usable AS (
  SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND list_bool_and(list_transform(embedding, lambda x: x IS NOT NULL AND isfinite(x))) AND list_bool_or(list_transform(embedding, lambda x: x <> 0))
), links AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM usable a JOIN usable b ON a.vec_id <> b.vec_id WHERE list_cosine_similarity(a.v, b.v) >= 0.95
), reach AS (
  SELECT vec_id AS a, vec_id AS b FROM embeddings UNION SELECT r.a, l.b FROM reach r JOIN links l ON l.a = r.b
), counted AS (
  SELECT a, count(*) AS n FROM links GROUP BY a
)
SELECT r.a AS vec_id, coalesce(any_value(c.n), 0) AS n_links, min(r.b) AS component_id, min(r.b) = r.a AS kept FROM reach r LEFT JOIN counted c ON c.a = r.a GROUP BY r.a
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_prefix_forest": op1_prefix_forest,
        "op2_factorization_machine": op2_factorization_machine,
        "op3_passage_chains": op3_passage_chains,
        "op4_token_shards": op4_token_shards,
        "op5_minhash_join": op5_minhash_join,
        "op6_sum_of_squares_packing": op6_sum_of_squares_packing,
        "op7_line_dedup": op7_line_dedup,
        "op8_tag_path_ratios": op8_tag_path_ratios,
        "op9_small_world": op9_small_world,
        "op10_byte_bpe": op10_byte_bpe,
    }


def oracle_sql() -> dict[str, str]:
    return {"op5_minhash_join": _OP5_SQL, "op7_line_dedup": _OP7_SQL, "op9_small_world": _OP9_SQL}
