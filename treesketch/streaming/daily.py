"""Sketches per window of an event stream; additivity makes them legal streaming aggregates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from treesketch.functions.fixedpoint import cents
from treesketch.functions.hashing import SketchSpec
from treesketch.sources import scratch

EVENTS = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])


def _cells(events: DataFrame, spec: SketchSpec, window: Column) -> DataFrame:
    coord = F.col("user_id").cast("long")
    lines = [F.struct(F.lit(r).alias("hrow"), spec.bucket(coord, r).alias("bucket"), (spec.sign(coord, r) * cents(F.col("value"))).alias("val")) for r in range(spec.rows)]
    rows = events.where((coord >= 0) & F.col("value").isNotNull()).select("ts", F.inline(F.array(*lines)))
    return rows.groupBy(window.alias("w"), "hrow", "bucket").agg(F.sum("val").alias("val"))


def windowed_sketch(events: DataFrame, spec: SketchSpec, *, length: str = "1 day", slide: str | None = None, watermark: str | None = "1 hour") -> DataFrame:
    """(w, hrow, bucket, val) for tumbling or sliding windows of ``events(ts, user_id, value)``, batch or stream.

    Times without zone are taken as the session's. Rows that come later than
    the watermark are dropped by Spark; earlier late rows are added to their
    window. A correction is another sketch that is added.
    """
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if watermark and events.isStreaming:
        timed = timed.withWatermark("ts", watermark)
    return _cells(timed, spec, F.window("ts", length, slide) if slide else F.window("ts", length))


def _by_day(cells: DataFrame) -> DataFrame:
    return cells.where(F.col("val") != 0).select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "hrow", "bucket", "val")


def daily_sketch(events: DataFrame, spec: SketchSpec) -> DataFrame:
    """(day, hrow, bucket, val) of a table of events."""
    return _by_day(windowed_sketch(events, spec, watermark=None))


def read_event_stream(spark: SparkSession, path: str, *, files_per_trigger: int | None = None) -> DataFrame:
    """Events as they arrive; ``path`` is a folder, or a table that is one file."""
    reader = spark.readStream.schema(EVENTS)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(path if not path.endswith(".parquet") else path + "*")


def stream_daily_sketch(spark: SparkSession, path: str, spec: SketchSpec, *, files_per_trigger: int | None = None) -> DataFrame:
    """The daily sketches of all that a stream holds now, in complete mode: all days, also the open one.

    Each micro-batch's whole result goes to a folder of its own in the shared
    folder, written by the executors; the last one is the result. A batch that
    is run again after a failure overwrites its folder.
    """
    at = scratch.scratch_path(spark, "daily")
    cells = windowed_sketch(read_event_stream(spark, path, files_per_trigger=files_per_trigger), spec)
    done: list[str] = []

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/{number}")
        done.append(f"{at}/{number}")

    query = cells.writeStream.foreachBatch(write).outputMode("complete").option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return _by_day(spark.read.schema(cells.schema).parquet(done[-1]) if done else spark.createDataFrame([], cells.schema))
