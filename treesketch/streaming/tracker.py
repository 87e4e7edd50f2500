"""Stateful operators on streams: a sketch and its heavy coordinates per key, and training on micro-batches."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from treesketch.functions.fixedpoint import cents
from treesketch.functions.hashing import SketchSpec
from treesketch.learning.trainer import np_top


def heavy_tracker(events: DataFrame, spec: SketchSpec, k: int, *, key: str = "event_type") -> DataFrame:
    """(key, coord, est): after each micro-batch the k coordinates (user ids) of largest estimate for every key that changed.

    A key's state is one sketch, whatever the number of its users, and the ids
    of its present k. Candidates are those and the micro-batch's own ids.
    """

    def update(name: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        cells, known = (np.array(state.get[0]), list(state.get[1])) if state.exists else (np.zeros(spec.size), [])
        fresh = []
        for part in parts:
            coord, val = part["coord"].to_numpy(), part["val"].to_numpy(np.float64)
            buckets, signs = spec.np_buckets(coord), spec.np_signs(coord)
            for r in range(spec.rows):
                cells[r * spec.width : (r + 1) * spec.width] += np.bincount(buckets[r], signs[r] * val, spec.width)
            fresh.append(np.unique(coord))
        asked = np.unique(np.concatenate([np.array(known, np.int64), *fresh]))
        buckets, signs = spec.np_buckets(asked), spec.np_signs(asked)
        est = np.sort(signs * np.take_along_axis(cells.reshape(spec.rows, spec.width), buckets, 1), axis=0)[spec.rows // 2]
        best = np_top(est, k)
        state.update((cells.tolist(), asked[best].tolist()))
        yield pd.DataFrame({"key": name[0], "coord": asked[best], "est": est[best]})

    rows = events.select(F.col(key).alias("key"), F.col("user_id").cast("long").alias("coord"), cents(F.col("value")).alias("val")).where(F.col("coord") >= 0)
    return rows.groupBy("key").applyInPandasWithState(update, "key string, coord long, est double", "cells array<double>, known array<long>", "update", GroupStateTimeout.NoTimeout)


def clicks_before_purchases(events: DataFrame, within: str = "1 hour", watermark: str = "1 hour") -> DataFrame:
    """(coord, val) of a sparse feed: users whose click is followed by a purchase in time, as a stream-stream interval join."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)
    a = timed.where(F.col("event_type") == "click").select(F.col("user_id").alias("u"), F.col("ts").alias("clicked"))
    b = timed.where(F.col("event_type") == "purchase").select("user_id", F.col("ts").alias("bought"), cents(F.col("value")).alias("val"))
    return a.join(b, (F.col("u") == F.col("user_id")) & (F.col("bought") >= F.col("clicked")) & (F.col("bought") <= F.col("clicked") + F.expr(f"INTERVAL {within}"))).select(F.col("user_id").alias("coord"), "val")


def train_on_stream(stream: DataFrame, step: Callable[[DataFrame, int], None], checkpoint: str):
    """Call ``step(micro_batch, number)`` for each micro-batch of all that the stream holds now: one training step each."""
    return stream.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def session_sketch(events: DataFrame, spec: SketchSpec, gap: str = "30 minutes") -> DataFrame:
    """(w, hrow, bucket, val) per session of a user: windows close after a gap."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if events.isStreaming:
        timed = timed.withWatermark("ts", "1 hour")
    coord = F.col("user_id").cast("long")
    sums = timed.where(coord >= 0).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.sum(cents(F.col("value"))).alias("v"))
    lines = [F.struct(F.lit(r).alias("hrow"), spec.bucket(coord, r).alias("bucket"), (spec.sign(coord, r) * F.col("v")).alias("val")) for r in range(spec.rows)]
    return sums.select("w", F.inline(F.array(*lines)))


