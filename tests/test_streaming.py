import pytest
from pyspark.sql import functions as F

from treesketch.functions.hashing import SketchSpec
from treesketch.operators import sketch as sk
from treesketch.sources.tables import read_table
from treesketch.streaming import daily, tracker

SPEC = SketchSpec(5, 64, 3)


@pytest.fixture(scope="module")
def parts(spark, tiny, tmp_path_factory):
    """The events in six files, in the order of time."""
    path = str(tmp_path_factory.mktemp("events"))
    events = read_table(spark, tiny, "events").orderBy("event_id")
    n = events.count()
    for i in range(6):
        events.where((F.col("event_id") >= i * n // 6) & (F.col("event_id") < (i + 1) * n // 6)).coalesce(1).write.mode("append").parquet(path)
    return path


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_stream_equals_batch(spark, tiny, parts):
    batch = rows(daily.daily_sketch(read_table(spark, tiny, "events"), SPEC))
    assert rows(daily.stream_daily_sketch(spark, parts, SPEC, files_per_trigger=1)) == batch


def test_append_gives_closed_days_only(spark, tiny, parts, tmp_path):
    cells = daily.windowed_sketch(daily.read_event_stream(spark, parts, files_per_trigger=1), SPEC)
    q = cells.writeStream.format("memory").queryName("closed").outputMode("append").option("checkpointLocation", str(tmp_path)).trigger(availableNow=True).start()
    q.awaitTermination()
    days = {r.day for r in daily._by_day(spark.table("closed")).collect()}
    every = {r.day for r in daily.daily_sketch(read_table(spark, tiny, "events"), SPEC).collect()}
    assert days < every and max(every) not in days


def test_days_add_up_to_the_whole(spark, tiny):
    events = read_table(spark, tiny, "events")
    by_day = daily.daily_sketch(events, SPEC).select("hrow", "bucket", "val")
    whole = sk.build(events.select(F.lit(0).alias("worker"), F.col("user_id").alias("coord"), F.floor(F.col("value") * 100 + 0.5).cast("long").alias("val")), SPEC)
    assert rows(sk.merge_flat(by_day)) == rows(sk.merge_flat(whole))


def test_sliding_windows_count_each_event_four_times(spark, tiny):
    events = read_table(spark, tiny, "events")
    once = daily.windowed_sketch(events, SPEC, watermark=None).where("hrow = 0").agg(F.sum("val")).first()[0]
    slid = daily.windowed_sketch(events, SPEC, slide="6 hours", watermark=None).where("hrow = 0").agg(F.sum("val")).first()[0]
    assert slid == 4 * once


def test_late_rows(spark, tmp_path):
    """Within the watermark a late row joins its window; beyond it, it is dropped."""
    src = str(tmp_path / "in")

    def put(i, ts):
        spark.sql(f"SELECT {i}L AS event_id, TIMESTAMP_NTZ '{ts}' AS ts, {i}L AS user_id, 'x' AS event_type, 1.0D AS value, '' AS props").coalesce(1).write.mode("append").parquet(src)

    def run():
        cells = daily.windowed_sketch(daily.read_event_stream(spark, src, files_per_trigger=1), SPEC)
        q = cells.writeStream.format("parquet").outputMode("append").option("checkpointLocation", str(tmp_path / "ck")).option("path", str(tmp_path / "out")).trigger(availableNow=True).start()
        q.awaitTermination()

    for i, ts in enumerate(["2024-01-01 10:00:00", "2024-01-02 00:30:00", "2024-01-01 23:50:00", "2024-01-03 05:00:00", "2024-01-01 12:00:00", "2024-01-05 00:00:00", "2024-01-06 00:00:00"]):
        put(i, ts)
        run()  # each run goes on from the checkpoint
    got = spark.read.parquet(str(tmp_path / "out")).where("hrow = 0").groupBy(F.date_format("w.start", "dd").alias("d")).agg(F.sum(F.abs("val")).alias("v")).collect()
    assert {r.d: r.v for r in got}["01"] == 200  # rows 0 and 2, not 4


def test_heavy_tracker_ends_with_the_true_top(spark, tiny, parts):
    wide = SketchSpec(5, 2048, 3)
    stream = daily.read_event_stream(spark, parts, files_per_trigger=2)
    q = tracker.heavy_tracker(stream, wide, 3).writeStream.format("memory").queryName("tops").outputMode("update").trigger(availableNow=True).start()
    q.awaitTermination()
    truth = read_table(spark, tiny, "events").groupBy("event_type", "user_id").agg(F.sum(F.floor(F.col("value") * 100 + 0.5)).alias("v"))
    best = {r.event_type: r.v for r in truth.groupBy("event_type").agg(F.max("v").alias("v")).collect()}
    seen = {r.key: r.e for r in spark.table("tops").groupBy("key").agg(F.max("est").alias("e")).collect()}
    assert set(seen) == set(best) and all(abs(seen[k] - best[k]) < 0.05 * best[k] for k in best)


def test_training_steps_follow_micro_batches(spark, parts, tmp_path):
    sizes = []
    q = tracker.train_on_stream(daily.read_event_stream(spark, parts, files_per_trigger=1), lambda df, i: sizes.append(df.count()), str(tmp_path))
    q.awaitTermination()
    assert sum(sizes) == 1000 and len(sizes) >= 6


def test_sessions(spark, tiny):
    cells = tracker.session_sketch(read_table(spark, tiny, "events"), SPEC)
    flat = sk.merge_flat(cells.select("hrow", "bucket", "val"))
    want = sk.merge_flat(daily.daily_sketch(read_table(spark, tiny, "events"), SPEC).select("hrow", "bucket", "val"))
    assert rows(flat) == rows(want)
