"""Exchange plans between workers: the halving tree with byes, and the star.

In a round of the halving tree worker 2j absorbs worker 2j + 1 and both become
participant j; the last of an odd number stays alone, a bye. So a round is a
sum grouped by ``worker >> 1``, for any number of workers.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treesketch.sources.literals import literal_grid, literal_rows


def rounds(workers: int) -> int:
    """ceil(log2(workers))."""
    if workers < 1:
        raise ValueError("there must be a worker")
    return (workers - 1).bit_length()


def tree_edges(spark: SparkSession, workers: int, direction: str = "up") -> DataFrame:
    """EDGE(direction, round, src, dst, kind) in original worker numbers; ``down`` copies back in reverse order."""
    if direction not in ("up", "down"):
        raise ValueError("direction is 'up' or 'down'")
    r = rounds(workers)
    steps = spark.range(workers).select(F.col("id").alias("w"), F.explode(F.sequence(F.lit(1), F.lit(r))).alias("round")) if r else spark.range(0).select(F.col("id").alias("w"), F.lit(1).alias("round"))
    stride = F.expr("shiftleft(1L, round - 1)")
    here = steps.where(F.col("w") % stride == 0)
    rank = F.floor(F.col("w") / stride).cast("long")
    count = F.floor((F.lit(workers) + stride - 1) / stride).cast("long")
    merge = here.where(rank % 2 == 1).select("round", F.col("w").alias("src"), (F.col("w") - stride).alias("dst"), F.lit("merge").alias("kind"))
    bye = here.where((rank % 2 == 0) & (rank == count - 1) & (count % 2 == 1) & (count > 1)).select("round", F.col("w").alias("src"), F.col("w").alias("dst"), F.lit("bye").alias("kind"))
    up = merge.unionByName(bye).select(F.lit("up").alias("direction"), F.col("round").cast("int").alias("round"), "src", "dst", "kind")
    if direction == "up":
        return up
    sent = up.where(F.col("kind") == "merge")
    return sent.select(F.lit("down").alias("direction"), (F.lit(r + 1) - F.col("round")).cast("int").alias("round"), F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit("copy").alias("kind"))


def literal_stride_coverage(spark: SparkSession, counts: list[int], held: DataFrame | None = None) -> DataFrame:
    """(workers, covered): how many workers reach the root if round i pairs ranks with stride i instead of 2^(i-1).

    A diagnostic: it loses workers from five on. ``held(workers, w)`` names the
    workers that have data, all of them if it is left out.
    """
    every = literal_grid(spark, workers=counts).select("workers", F.explode(F.sequence(F.lit(0).cast("long"), F.col("workers") - 1)).alias("w"))
    now = (every if held is None else held.select("workers", "w")).withColumn("at", F.array("w"))
    for i in range(1, rounds(max(counts)) + 1):
        # who stands on an odd one of the ranks 0, i, 2i, ... is also sent to the rank before
        sent = F.transform(F.filter("at", lambda x: (x % i == 0) & (F.floor(x / i) % 2 == 1)), lambda x: x - i)
        takes_part = F.lit(i) <= F.length(F.bin(F.col("workers") - 1)) * (F.col("workers") > 1).cast("int")
        now = now.withColumn("at", F.when(takes_part, F.array_distinct(F.concat("at", sent))).otherwise(F.col("at")))
    return now.groupBy(F.col("workers").cast("int").alias("workers")).agg(F.count_if(F.array_contains("at", 0)).cast("int").alias("covered"))


def tree_merge(table: DataFrame, workers: int, keys: tuple[str, ...] = ("hrow", "bucket"), *, partitions: int | None = None) -> DataFrame:
    """Sum (worker, *keys, val) along the halving tree; the result has no worker.

    One shuffle on the keys places all that is ever summed together; the
    rounds' aggregates then run inside their partitions, whose number defaults
    to the session's. Sums of BIGINT equal the flat merge exactly.
    """
    spark = table.sparkSession
    now = table.select(F.col("worker").cast("long").alias("worker"), *keys, "val")
    now = now.repartition(partitions or int(spark.conf.get("spark.sql.shuffle.partitions")), *keys)
    for _ in range(rounds(workers)):
        now = now.groupBy(F.shiftright("worker", 1).alias("worker"), *keys).agg(F.sum("val").alias("val"))
    return now.groupBy(*keys).agg(F.sum("val").alias("val")).where(F.col("val") != 0)


def star_merge(table: DataFrame, keys: tuple[str, ...] = ("hrow", "bucket")) -> DataFrame:
    """The same sum as all workers' uploads to one server."""
    return table.groupBy(*keys).agg(F.sum("val").alias("val")).where(F.col("val") != 0)


def counted_ledger(table: DataFrame, workers: int, keys: tuple[str, ...] = ("hrow", "bucket"), *, values_per_row: int = 1) -> DataFrame:
    """(round, messages, values): what really crosses the tree's upward links, counted on the data.

    An absent worker still sends a message, with no values. Sparse cells are
    counted as they are; a dense message has rows * width values whatever they are.
    """
    spark = table.sparkSession
    out = None
    now = table.select(F.col("worker").cast("long").alias("worker"), *keys, "val")
    count = workers
    for i in range(1, rounds(workers) + 1):
        sent = now.where(F.col("worker") % 2 == 1).agg(F.count(F.lit(1)).alias("n"))
        line = sent.select(F.lit(i).alias("round"), F.lit(count // 2).cast("long").alias("messages"), (F.col("n") * values_per_row).alias("values"))
        out = line if out is None else out.unionByName(line)
        now = now.groupBy(F.shiftright("worker", 1).alias("worker"), *keys).agg(F.sum("val").alias("val")).where(F.col("val") != 0)
        count = (count + 1) // 2
    return out if out is not None else literal_rows(spark, [], "round int, messages long, values long")


def ledger_lines(method: str, workers: int, *, d: int, k: int, size: int, union: int | None = None) -> list[tuple]:
    """(method, phase, direction, round, messages, values) of one exchange by closed form.

    ``size`` is rows * width; ``union`` the coordinates of all uploads of a
    star, k * workers if not measured. A coordinate counts as one value.
    """
    r, p = rounds(workers), workers
    lines: list[tuple] = []

    def tree(phase: str, values: int) -> None:
        count, up = p, []
        for i in range(1, r + 1):
            up.append((i, count // 2))
            count = (count + 1) // 2
        lines.extend((method, phase, "up", i, m, m * values) for i, m in up)
        lines.extend((method, phase, "down", r + 1 - i, m, m * values) for i, m in reversed(up))

    def star(phase: str, up: int, down: int) -> None:
        lines.append((method, phase, "up", 1, p, p * up))
        lines.append((method, phase, "down", 1, p, p * down))

    if method == "dense":
        tree("dense", d)
    elif method == "tree_topk":
        tree("sparse", 2 * k)
    elif method == "star_topk":
        star("sparse", 2 * k, 2 * (k * p if union is None else union))
    elif method == "tree_sketch":
        tree("sketch", size)
        tree("exact", k)
    elif method == "star_sketch":
        star("sketch", size, size)
        star("exact", k, k)
    else:
        raise ValueError(f"unknown method {method}")
    return lines


def ledger_of(sizes: DataFrame, methods: list[str], counts: list[int]) -> DataFrame:
    """The ledger of exchanges whose d, k and size are columns of ``sizes``; what a line sends is linear in them."""
    spark = sizes.sparkSession
    lines = []
    for p in counts:
        for m in methods:
            units = [ledger_lines(m, p, **({"d": 0, "k": 0, "size": 0} | {c: 1})) for c in ("d", "k", "size")]
            lines += [(p, *one[0][:5], *(x[5] for x in one)) for one in zip(*units)]
    known = literal_rows(spark, lines, "workers int, method string, phase string, direction string, round int, messages long, per_d long, per_k long, per_size long")
    values = (F.col("per_d") * F.col("d") + F.col("per_k") * F.col("k") + F.col("per_size") * F.col("size")).alias("values")
    out = known.crossJoin(F.broadcast(sizes.select("d", "k", "size"))).select("workers", "method", "phase", "direction", "round", "messages", values)
    return out.withColumn("bytes", F.col("values") * 8)


def ledger(spark: SparkSession, methods: list[str], counts: list[int], *, d: int, k: int, size: int) -> DataFrame:
    """LEDGER(workers, method, phase, direction, round, messages, values, bytes) for every method and worker count, eight bytes a value."""
    lines = [(p, *line) for p in counts for m in methods for line in ledger_lines(m, p, d=d, k=k, size=size)]
    schema = "workers int, method string, phase string, direction string, round int, messages long, values long"
    return literal_rows(spark, lines, schema).withColumn("bytes", F.col("values") * 8)
