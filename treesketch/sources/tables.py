"""The given tables by name, and the vectors and examples made from them."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from treesketch.functions.fixedpoint import cents, to_fixed
from treesketch.functions.hashing import fill_order

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
#: Columns that the vectors need, by table; read_table checks them.
NEEDED = {
    "lineitem": {"l_orderkey": T.LongType, "l_partkey": T.LongType, "l_quantity": T.DoubleType},
    "documents": {"doc_id": T.LongType, "text": T.StringType},
    "embeddings": {"vec_id": T.LongType, "embedding": T.ArrayType},
    "events": {"event_id": T.LongType, "user_id": T.LongType, "value": T.DoubleType},
}
#: Letters that make words; anything else parts them.
NOT_A_WORD = "[^a-zà-ÿß]+"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    for column, kind in NEEDED.get(name, {}).items():
        if column not in df.columns or not isinstance(df.schema[column].dataType, kind):
            raise TypeError(f"{name}.{column} must be a {kind.__name__}")
    return df


def read_any(spark: SparkSession, path: str, kind: str = "parquet", **options) -> DataFrame:
    """A table of another format that Spark reads: csv, json, orc, ..."""
    return spark.read.format(kind).options(**options).load(path)


def part_vector(spark: SparkSession, sf_dir: str, workers: int = 4, *, summed: bool = True) -> DataFrame:
    """Whole quantities per part: a flat vector without heavy coordinates.

    ``summed=False`` leaves the lines as they are: a sketch is linear, so it
    needs no shuffle by coordinate first.
    """
    rows = read_table(spark, sf_dir, "lineitem").select(F.pmod("l_orderkey", F.lit(workers)).cast("int").alias("worker"), F.col("l_partkey").alias("coord"), F.col("l_quantity").cast("long").alias("val"))
    return rows.groupBy("worker", "coord").agg(F.sum("val").alias("val")) if summed else rows


def vector_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vector, d): coordinates of the lines' vectors by part, supplier and order; d is the largest key and one."""
    lines = read_table(spark, sf_dir, "lineitem")
    most = lines.agg(*[(F.max(c) + 1).alias(c) for c in ("l_partkey", "l_suppkey", "l_orderkey")])
    return most.select(F.inline(F.array(*[F.struct(F.lit(n).alias("vector"), F.col(c).alias("d")) for n, c in (("parts", "l_partkey"), ("suppliers", "l_suppkey"), ("orders", "l_orderkey"))]))).where(F.col("d").isNotNull())


def lines_by_worker(spark: SparkSession, sf_dir: str, counts: list[int]) -> DataFrame:
    """(workers, w, lines): the lines that each worker holds, for several numbers of workers at once."""
    by = math.lcm(*counts)
    few = read_table(spark, sf_dir, "lineitem").where(F.col("l_orderkey").isNotNull()).groupBy(F.pmod("l_orderkey", F.lit(by).cast("long")).alias("m")).agg(F.count(F.lit(1)).alias("n"))
    each = few.select("m", "n", F.explode(F.array(*[F.lit(c).cast("long") for c in counts])).alias("workers"))
    return each.groupBy("workers", (F.col("m") % F.col("workers")).alias("w")).agg(F.sum("n").alias("lines"))


def price_vector(spark: SparkSession, sf_dir: str, workers: int = 4, *, summed: bool = True) -> DataFrame:
    """Cents per part, negative for returned lines: signed values; ``summed`` as in ``part_vector``."""
    amount = cents(F.col("l_extendedprice")) * F.when(F.col("l_returnflag") == "R", -1).otherwise(1)
    rows = read_table(spark, sf_dir, "lineitem").select(F.pmod("l_orderkey", F.lit(workers)).cast("int").alias("worker"), F.col("l_partkey").alias("coord"), amount.cast("long").alias("val"))
    return rows.groupBy("worker", "coord").agg(F.sum("val").alias("val")) if summed else rows


def words(text: Column) -> Column:
    return F.split(F.lower(text), NOT_A_WORD)


def word_coordinate(word: Column, d: int) -> Column:
    """The first 32 bits of the word's MD5, modulo d; the same in DuckDB."""
    return F.conv(F.substring(F.md5(word), 1, 8), 16, 10).cast("long") % d


def token_vector(spark: SparkSession, sf_dir: str, workers: int = 5, d: int = 4096) -> DataFrame:
    """Counts of hashed words of all documents: a skewed vector. Words are counted before they are hashed."""
    docs = read_table(spark, sf_dir, "documents").select(F.pmod("doc_id", F.lit(workers)).cast("int").alias("worker"), F.explode(words(F.col("text"))).alias("word"))
    counted = docs.where(F.col("word") != "").groupBy("worker", "word").agg(F.count(F.lit(1)).alias("n"))
    return counted.groupBy("worker", word_coordinate(F.col("word"), d).alias("coord")).agg(F.sum("n").alias("val"))


def event_vector(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    """Cents per user of all events."""
    rows = read_table(spark, sf_dir, "events").select(F.pmod("event_id", F.lit(workers)).cast("int").alias("worker"), F.col("user_id").alias("coord"), cents(F.col("value")).alias("val"))
    return rows.groupBy("worker", "coord").agg(F.sum("val").alias("val"))


def property_vector(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    """Events per whole number ``k`` in their JSON properties; other properties are left out."""
    k = F.try_parse_json("props")
    rows = read_table(spark, sf_dir, "events").select(F.pmod("event_id", F.lit(workers)).cast("int").alias("worker"), F.try_variant_get(k, "$.k", "long").alias("coord"))
    return rows.where(F.col("coord").isNotNull()).groupBy("worker", "coord").agg(F.count(F.lit(1)).alias("val"))


#: Classes and components of the planted problem.
CLASSES, COMPONENTS = 10, 64


def teacher_weight(cell: Column) -> Column:
    """Whole weights in -1000 .. 1000 of a fixed linear teacher; cell = class * COMPONENTS + component."""
    return fill_order(cell.cast("long"), 99, 0) % 2001 - 1000


def fixed_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(key, j, x): the embeddings' components as whole multiples of 2^-20."""
    rows = read_table(spark, sf_dir, "embeddings").where(F.col("embedding").isNotNull())
    return rows.select(F.col("vec_id").alias("key"), F.posexplode("embedding").alias("j", "v")).select("key", F.col("j").cast("long").alias("j"), to_fixed(F.col("v").cast("double")).alias("x"))


def planted_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(key, label): the teacher's class with the largest whole score, ties to the smaller class."""
    scores = fixed_components(spark, sf_dir).crossJoin(F.broadcast(spark.range(CLASSES).select(F.col("id").alias("c"))))
    summed = scores.groupBy("key", "c").agg(F.sum(F.col("x") * teacher_weight(F.col("c") * COMPONENTS + F.col("j"))).alias("s"))
    return summed.groupBy("key").agg(F.max_by("c", F.struct("s", -F.col("c"))).cast("int").alias("label"))
