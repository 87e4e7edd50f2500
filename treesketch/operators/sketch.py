"""The signed-bucket sketch as a table of cells, and as one row of all cells.

COORD is (worker, coord, val), SKETCH is (worker, hrow, bucket, val). A missing
cell is 0 and zero cells are not kept, so equal sketches are equal tables.
Values are BIGINT in exact mode and DOUBLE in real mode.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from treesketch.functions.hashing import PRIME, SketchSpec
from treesketch.functions.fixedpoint import wide

#: Cells that a block (one row, broadcast as such) may have: 32 MB of numbers.
MAX_BLOCK_CELLS = 1 << 22


def _faults(coords: DataFrame) -> dict[str, Column]:
    """What makes a row of COORD unfit, by name; the first that holds counts."""
    real = dict(coords.dtypes)["val"] in ("double", "float")
    faults = {
        "no coordinate": F.col("coord").isNull(), "coordinate out of range": (F.col("coord") < 0) | (F.col("coord") >= PRIME), "no value": F.col("val").isNull(),
        "value not finite": F.isnan("val") | (F.abs("val") == float("inf")) if real else F.lit(False),
    }
    return faults


def valid(coords: DataFrame) -> DataFrame:
    """Rows with a coordinate in [0, 2^31 - 1) and a value that is a finite number; ``rejected`` counts the others.

    Keys beyond that range are folded into it first, with ``hashing.fold_domain``.
    """
    unfit = F.lit(False)
    for fault in _faults(coords).values():
        unfit = unfit | F.coalesce(fault, F.lit(False))
    return coords.where(~unfit)


def rejected(coords: DataFrame) -> DataFrame:
    """(reason, n) of the rows that ``valid`` leaves out; no row for a reason that none has."""
    reason = F.lit(None).cast("string")
    for name, fault in reversed(list(_faults(coords).items())):
        reason = F.when(fault, F.lit(name)).otherwise(reason)
    return coords.select(reason.alias("reason")).where(F.col("reason").isNotNull()).groupBy("reason").agg(F.count(F.lit(1)).alias("n"))


def checked(coords: DataFrame) -> DataFrame:
    """``coords`` as they are; a row that ``valid`` would leave out stops the job."""
    reason = F.lit(None).cast("string")
    for name, fault in _faults(coords).items():
        reason = F.coalesce(reason, F.when(fault, F.lit(name)))
    stop = F.raise_error(F.concat(F.lit("unfit row: "), reason)).cast("boolean")
    return coords.where(F.when(reason.isNotNull(), stop).otherwise(F.lit(True)))


def _nonzero_sum(df: DataFrame, by: Sequence[str]) -> DataFrame:
    return df.groupBy(*by).agg(F.sum("val").alias("val")).where(F.col("val") != 0)


def build(coords: DataFrame, spec: SketchSpec, by: Sequence[str] = ("worker",)) -> DataFrame:
    """Add sign * value to one bucket of each row.

    The map-side aggregate is each task's own sketch; the shuffle carries at
    most rows * width cells of a task and group.
    """
    coord = F.col("coord").cast("long")
    lines = [F.struct(F.lit(r).alias("hrow"), spec.bucket(coord, r).alias("bucket"), (spec.sign(coord, r) * F.col("val")).alias("val")) for r in range(spec.rows)]
    return _nonzero_sum(valid(coords).select(*by, F.inline(F.array(*lines))), [*by, "hrow", "bucket"])


def build_sql(view: str, spec: SketchSpec, *, coord: str = "coord", val: str = "val", by: Sequence[str] = ("worker",)) -> str:
    """The same as SQL text, for Spark and DuckDB alike: rows of coefficients joined to a view."""
    keys = ", ".join([*by, "hrow"])
    return (
        f"WITH {spec.sql_rows()} SELECT {keys}, {spec.sql_bucket(coord)} AS bucket, CAST(sum({spec.sql_sign(coord)} * {val}) AS BIGINT) AS val "
        f"FROM {view} CROSS JOIN hash_rows WHERE {coord} >= 0 GROUP BY {keys}, {spec.sql_bucket(coord)} HAVING sum({spec.sql_sign(coord)} * {val}) <> 0"
    )


def build_blocks(coords: DataFrame, spec: SketchSpec) -> DataFrame:
    """Partial sketches by NumPy: a row of (worker, cells binary) for each task and worker; cells are doubles, row by row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            worker, coord, val = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(3))
            buckets, signs = spec.np_buckets(coord), spec.np_signs(coord)
            for w in np.unique(worker):
                mine = worker == w
                cells = sums.setdefault(int(w), np.zeros(spec.size))
                for r in range(spec.rows):
                    cells[r * spec.width : (r + 1) * spec.width] += np.bincount(buckets[r, mine], signs[r, mine] * val[mine], spec.width)
        if sums:
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([c.tobytes() for c in sums.values()], pa.binary())], names=["worker", "cells"])

    rows = valid(coords).select(F.col("worker").cast("int").alias("worker"), F.col("coord").cast("long").alias("coord"), F.col("val").cast("double").alias("val"))
    return rows.mapInArrow(run, "worker int, cells binary")


def cells_of_blocks(blocks: DataFrame, spec: SketchSpec) -> DataFrame:
    """SKETCH rows of partial blocks, summed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for worker, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                cells = np.frombuffer(raw)
                at = np.flatnonzero(cells)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), worker, np.int32)), pa.array((at // spec.width).astype(np.int32)), pa.array((at % spec.width).astype(np.int32)), pa.array(cells[at])], names=["worker", "hrow", "bucket", "val"])

    return _nonzero_sum(blocks.mapInArrow(run, "worker int, hrow int, bucket int, val double"), ["worker", "hrow", "bucket"])


def add(*sketches: DataFrame) -> DataFrame:
    """The sketch of the sum of the vectors: cells are summed."""
    out = sketches[0]
    for s in sketches[1:]:
        out = out.unionByName(s)
    return _nonzero_sum(out, [c for c in sketches[0].columns if c != "val"])


def scale(sketch: DataFrame, factor: int | float) -> DataFrame:
    return sketch.withColumn("val", F.col("val") * F.lit(factor)).where(F.col("val") != 0)


def subtract(a: DataFrame, b: DataFrame) -> DataFrame:
    return add(a, scale(b, -1))


def merge_flat(sketch: DataFrame) -> DataFrame:
    """All workers' cells summed in one shuffle: (hrow, bucket, val)."""
    return _nonzero_sum(sketch, ["hrow", "bucket"])


def block(sketch: DataFrame, spec: SketchSpec) -> DataFrame:
    """One row ``cells array`` of a merged sketch, row after row; its size is fixed by the spec and checked."""
    if spec.size > MAX_BLOCK_CELLS:
        raise ValueError(f"{spec.size} cells are more than a block may have ({MAX_BLOCK_CELLS})")
    kind = dict(sketch.dtypes)["val"]
    at = (F.col("hrow") * spec.width + F.col("bucket")).alias("k")
    pairs = sketch.agg(F.array_sort(F.collect_list(F.struct(at, F.col("val").alias("v")))).alias("p"))
    zeros = lambda n: F.array_repeat(F.lit(0).cast(kind), n.cast("int"))
    one = lambda x, i: F.concat(zeros(x["k"] - F.when(i == 0, F.lit(0)).otherwise(F.get("p", i - 1)["k"] + 1)), F.array(x["v"]))
    last = F.when(F.size("p") > 0, F.get("p", F.size("p") - 1)["k"]).otherwise(F.lit(-1))
    return pairs.select(F.concat(F.flatten(F.transform("p", one)), zeros(F.lit(spec.size - 1) - last)).alias("cells"))


def middle(values: Column, n: int) -> Column:
    """The middle element of an array of an odd number of values."""
    return F.element_at(F.array_sort(values), (n + 1) // 2)


def estimate_blocks(sketch: DataFrame, spec: SketchSpec, candidates: DataFrame) -> DataFrame:
    """(coord, est) for each row of ``candidates(coord)``: the cells go along as one broadcast row, nothing is shuffled."""
    coord = F.col("coord").cast("long")
    reads = [spec.sign(coord, r) * F.element_at("cells", spec.bucket(coord, r) + (r * spec.width + 1)) for r in range(spec.rows)]
    return candidates.select("coord").crossJoin(F.broadcast(block(sketch, spec))).select("coord", middle(F.array(*reads), spec.rows).alias("est"))


def estimate_with_norm(sketch: DataFrame, spec: SketchSpec, candidates: DataFrame) -> DataFrame:
    """(coord, est, l2sq) from one pass over the cells: the norm is taken from the broadcast row as well."""
    exact = dict(sketch.dtypes)["val"] not in ("double", "float")
    kind = "decimal(38,0)" if exact else "double"
    square = lambda s, x: (s + x.cast(kind) * x.cast(kind)).cast(kind)
    sums = [F.aggregate(F.slice("cells", r * spec.width + 1, spec.width), F.lit(0).cast(kind), square) for r in range(spec.rows)]
    whole = block(sketch, spec).select("cells", middle(F.array(*sums), spec.rows).alias("l2sq"))
    coord = F.col("coord").cast("long")
    reads = [spec.sign(coord, r) * F.element_at("cells", spec.bucket(coord, r) + (r * spec.width + 1)) for r in range(spec.rows)]
    return candidates.select("coord").crossJoin(F.broadcast(whole)).select("coord", middle(F.array(*reads), spec.rows).alias("est"), "l2sq")


def estimate(sketch: DataFrame, spec: SketchSpec, candidates: DataFrame) -> DataFrame:
    """The same by a join on (hrow, bucket), for sketches beyond a block. A missing cell reads as 0."""
    coord = F.col("coord").cast("long")
    lines = [F.struct(F.lit(r).alias("hrow"), spec.bucket(coord, r).alias("bucket"), spec.sign(coord, r).alias("sign")) for r in range(spec.rows)]
    asked = candidates.select("coord", F.inline(F.array(*lines)))
    read = F.coalesce(F.col("sign") * F.col("val"), F.lit(0).cast(dict(sketch.dtypes)["val"]))
    return asked.join(sketch, ["hrow", "bucket"], "left").groupBy("coord").agg(middle(F.collect_list(read), spec.rows).alias("est"))


def l2_squared(sketch: DataFrame, spec: SketchSpec) -> DataFrame:
    """One row ``l2sq``: the median over rows of the sums of squared cells; a row without cells counts as 0."""
    exact = dict(sketch.dtypes)["val"] not in ("double", "float")
    val = wide(F.col("val")) if exact else F.col("val")
    kind = "decimal(38,0)" if exact else "double"
    sums = [F.coalesce(F.sum(F.when(F.col("hrow") == r, val * val)), F.lit(0)).cast(kind) for r in range(spec.rows)]
    return sketch.agg(middle(F.array(*sums), spec.rows).alias("l2sq"))


def dimension(spark, d: int) -> DataFrame:
    """All coordinates 0 .. d - 1."""
    return spark.range(d).select(F.col("id").alias("coord"))
