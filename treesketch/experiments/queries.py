"""The driver's queries: each method, variant, baseline and measure on the given tables.

Outputs are whole numbers and strings, ties are broken, so that they equal
their SQL twins in ``oracles`` value by value.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treesketch.functions import cost, sparse
from treesketch.functions.fixedpoint import cents, micro
from treesketch.functions.hashing import SketchSpec, size_for
from treesketch.learning import gradients, schedule
from treesketch.operators import compressors, measures, recovery, topology
from treesketch.operators import sketch as sk
from treesketch.plans.steps import apply_update, residual, sketch_step
from treesketch.sources import tables
from treesketch.sources.literals import literal_rows
from treesketch.streaming import daily

Query = Callable[[SparkSession, str], DataFrame]

#: Sketch and sizes of the queries: token vectors have D coordinates, five workers and keep K.
SPEC, D, K = SketchSpec(rows=5, width=256, seed=7), 4096, 100
WIDE = SketchSpec(rows=5, width=1024, seed=7)
SEED, STEP = 1, 1
PARTS = 20_000
TREE_SIZES = [1, 2, 3, 4, 5, 6, 7, 8, 9, 16]
GRID = {"workers": [2, 3, 4, 5, 8, 16, 64], "densities_ppm": [250_000, 72_500, 15_000, 4_000], "alphas": [10**4, 10**5]}
#: Density of the ledgers' messages, and the one point of the grid whose rates ``speedup_table`` compares.
LEDGER_PPM = 4_000
RATED = {"workers": [4], "densities_ppm": [15_000], "alphas": [10**4]}


def _tokens(spark: SparkSession, sf: str, workers: int = 5) -> DataFrame:
    return tables.token_vector(spark, sf, workers, D)


def _merged_tokens(spark: SparkSession, sf: str, spec: SketchSpec = SPEC) -> DataFrame:
    return sk.merge_flat(sk.build(_tokens(spark, sf), spec))


def _token_estimates(spark: SparkSession, sf: str, spec: SketchSpec = SPEC) -> DataFrame:
    return sk.estimate_blocks(_merged_tokens(spark, sf, spec), spec, sk.dimension(spark, D))


def _token_split(spark: SparkSession, sf: str) -> DataFrame:
    return recovery.split_heavy(_token_estimates(spark, sf), sk.l2_squared(_merged_tokens(spark, sf), SPEC), K)


def _token_support(spark: SparkSession, sf: str) -> DataFrame:
    return recovery.heavy_random(_token_split(spark, sf), K, SEED, STEP)


def _tree(workers: int) -> Query:
    return lambda spark, sf: topology.tree_merge(sk.build(tables.part_vector(spark, sf, workers, summed=False), SPEC), workers)


def _ledgers(spark: SparkSession, sf: str) -> DataFrame:
    """The ledger of the lines' vector by part, as large as the table has it."""
    k = F.greatest(F.lit(1).cast("long"), F.floor((F.col("d") * LEDGER_PPM + 999_999) / 1_000_000).cast("long"))
    sizes = tables.vector_sizes(spark, sf).where(F.col("vector") == "parts").select("d", k.alias("k"), F.lit(SPEC.size).cast("long").alias("size"))
    return topology.ledger_of(sizes, list(cost.METHODS), TREE_SIZES)


def _edges(spark: SparkSession, sf: str) -> DataFrame:
    """The tree's edges, and how many lines of the table are in what an edge carries: those of the ranks merged so far, on the way back all."""
    out = None
    for p in TREE_SIZES:
        for direction in ("up", "down"):
            one = topology.tree_edges(spark, p, direction).withColumn("workers", F.lit(p))
            out = one if out is None else out.unionByName(one)
    held = tables.lines_by_worker(spark, sf, TREE_SIZES).withColumnRenamed("workers", "p")
    carried = (F.col("p") == F.col("workers")) & ((F.col("direction") == "down") | F.col("w").between(F.col("src"), F.col("src") + F.expr("shiftleft(1L, round - 1)") - 1))
    by = ["workers", "direction", "round", "src", "dst", "kind"]
    edges = out.select("workers", "direction", "round", F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), "kind")
    return edges.join(F.broadcast(held), carried, "left").groupBy(*by).agg(F.coalesce(F.sum("lines"), F.lit(0)).cast("long").alias("lines"))


def sketch_subtract(spark: SparkSession, sf: str) -> DataFrame:
    """Quantities less cents: the difference of two sketches is the sketch of the difference."""
    a, b = (sk.build(v, SPEC) for v in (tables.part_vector(spark, sf, summed=False), tables.price_vector(spark, sf, summed=False)))
    return sk.subtract(a, b)


def sketch_norm(spark: SparkSession, sf: str) -> DataFrame:
    flat, skewed = sk.merge_flat(sk.build(tables.part_vector(spark, sf, summed=False), SPEC)), _merged_tokens(spark, sf)
    named = lambda s, n: sk.l2_squared(s, SPEC).select(F.lit(n).alias("vector"), F.col("l2sq").cast("long").alias("l2sq"))
    return named(flat, "parts").unionByName(named(skewed, "tokens"))


def point_query(spark: SparkSession, sf: str) -> DataFrame:
    vector = tables.part_vector(spark, sf, summed=False)
    return sk.estimate(sk.merge_flat(sk.build(vector, SPEC)), SPEC, vector.select("coord").distinct())


def sketch_sizes(spark: SparkSession, sf: str) -> DataFrame:
    """The sketches that the lines' vectors need; only the rows depend on d."""
    asked = [(p, form, size_for(10**3, p / 100, form=form).width) for p in (2, 5, 10) for form in ("inverse_square", "inverse_eps")]
    r = F.ceil(F.log2(F.col("d") / 0.05)).cast("int")
    sizes = tables.vector_sizes(spark, sf).select("vector", "d", F.when(r % 2 == 1, r).otherwise(r + 1).alias("sketch_rows"))
    return sizes.crossJoin(literal_rows(spark, asked, "eps_percent int, form string, width int"))


def sketch_blocks(spark: SparkSession, sf: str) -> DataFrame:
    """The NumPy path's cells as whole numbers: equal to those of the relational path."""
    cells = sk.cells_of_blocks(sk.build_blocks(tables.part_vector(spark, sf, summed=False), SPEC), SPEC)
    return cells.select("worker", "hrow", "bucket", F.col("val").cast("long").alias("val"))


def sketch_sql(spark: SparkSession, sf: str) -> DataFrame:
    tables.part_vector(spark, sf, summed=False).createOrReplaceTempView("treesketch_parts")
    return spark.sql(sk.build_sql("treesketch_parts", SPEC))


def tree_dense(spark: SparkSession, sf: str) -> DataFrame:
    return topology.tree_merge(tables.part_vector(spark, sf, 5), 5, ("coord",))


def speedup_table(spark: SparkSession, sf: str) -> DataFrame:
    """Rates of modelled exchanges of the lines' vectors, and the speed-up of tree-sketch in them."""
    sizes = tables.vector_sizes(spark, sf)
    times = cost.grid(spark, dims=sizes, **RATED).join(sizes, "d")
    rates = times.select(F.col("vector").alias("model"), "method", (F.lit(1e9) / F.col("t")).alias("examples_per_s"))
    ratios = measures.speedup(rates, "tree_sketch", "tree_topk").unionByName(measures.speedup(rates, "tree_sketch", "star_sketch"))
    mean = measures.mean_speedup(ratios).select(F.lit("mean").alias("model"), "method", "over", F.col("mean_speedup").alias("speedup"))
    return ratios.unionByName(mean).select("model", "over", micro(F.col("speedup")).alias("speedup_micro"))


def cost_speedup(spark: SparkSession, sf: str) -> DataFrame:
    g = cost.grid(spark, dims=tables.vector_sizes(spark, sf), **GRID)
    by = ["workers", "d", "k", "size", "alpha"]
    wide = g.groupBy(*by).agg(*[F.max(F.when(F.col("method") == m, F.col("t"))).alias(m) for m in cost.METHODS])
    wins = cost.tree_sketch_wins(F.col("k"), F.col("size"), F.col("alpha"), F.lit(1))
    ratio = lambda m: micro(F.col(m) / F.col("tree_sketch")).alias(f"over_{m}_micro")
    return wide.select(*by, *[ratio(m) for m in cost.METHODS if m != "tree_sketch"], wins.cast("int").alias("beats_tree_topk"))


def compression(spark: SparkSession, sf: str) -> DataFrame:
    """What the largest message of a worker has, counted on the token vectors."""
    top = compressors.local_topk(_tokens(spark, sf), K).groupBy("worker").agg(F.count(F.lit(1)).alias("n")).agg((2 * F.max("n")).alias("top"))
    support = _token_support(spark, sf).agg((F.count(F.lit(1)) + SPEC.size).alias("sketch"))
    values = {"dense": F.lit(D).cast("long"), "star_topk": F.col("top"), "tree_topk": F.col("top"), "star_sketch": F.col("sketch"), "tree_sketch": F.col("sketch")}
    sent = top.crossJoin(support).select(F.inline(F.array(*[F.struct(F.lit(m).alias("method"), v.alias("values")) for m, v in values.items()])))
    return measures.compression_ratio(D, sent)


def warmup_days(spark: SparkSession, sf: str) -> DataFrame:
    """The warm-up over the days of the events, an epoch a day."""
    days = tables.read_table(spark, sf, "events").select(F.to_date("ts").alias("day")).where(F.col("day").isNotNull()).distinct()
    epochs = days.crossJoin(days.agg(F.min("day").alias("first"))).select(F.date_diff("day", "first").alias("epoch"))
    return schedule.warmup_schedule(spark, epochs, 16_384, 1024, 500)


def minibatch(spark: SparkSession, sf: str) -> DataFrame:
    rows = tables.read_table(spark, sf, "embeddings").select(F.col("vec_id").alias("key"), schedule.worker_of(F.col("vec_id"), 4).alias("worker"))
    return schedule.minibatch(rows, 3, 16, SEED)


def shard_counts(spark: SparkSession, sf: str) -> DataFrame:
    rows = tables.read_table(spark, sf, "documents")
    return rows.groupBy(schedule.worker_of(F.col("doc_id"), 4).alias("worker")).agg(F.count(F.lit(1)).alias("n"))


def estimate_error(spark: SparkSession, sf: str) -> DataFrame:
    truth = compressors.dense_sum(_tokens(spark, sf))
    out = None
    for spec in (SPEC, WIDE):
        one = measures.estimate_error(_token_estimates(spark, sf, spec), truth).withColumn("width", F.lit(spec.width))
        out = one if out is None else out.unionByName(one)
    return out


def heavy_recall(spark: SparkSession, sf: str) -> DataFrame:
    return measures.heavy_recall(_token_support(spark, sf), compressors.dense_sum(_tokens(spark, sf)), K)


def support_overlap(spark: SparkSession, sf: str) -> DataFrame:
    top = compressors.exact_topk(_tokens(spark, sf), K)
    ways = {"heavy_random": _token_support(spark, sf), "top_estimate": recovery.top_estimate(_token_estimates(spark, sf), K)}
    out = None
    for name, support in ways.items():
        one = measures.support_overlap(support, top).withColumn("recovery", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


def captured_energy(spark: SparkSession, sf: str) -> DataFrame:
    return measures.captured_energy(recovery.top_estimate(_token_estimates(spark, sf), K), compressors.dense_sum(_tokens(spark, sf)))


def ledger_rollup(spark: SparkSession, sf: str) -> DataFrame:
    sums = _ledgers(spark, sf).rollup("method", "phase").agg(F.sum("messages").alias("messages"), F.sum("values").alias("values"), F.sum("bytes").alias("bytes"))
    return sums.select(F.coalesce("method", F.lit("all")).alias("method"), F.coalesce("phase", F.lit("all")).alias("phase"), "messages", "values", "bytes")


def event_session_counts(spark: SparkSession, sf: str) -> DataFrame:
    """Sessions of each user with gaps below 30 minutes."""
    events = tables.read_table(spark, sf, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"), cents(F.col("value")).alias("val"))
    sessions = events.groupBy("user_id", F.session_window("ts", "30 minutes").alias("s")).agg(F.count(F.lit(1)).alias("n"), F.sum("val").alias("val"))
    return sessions.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("n").alias("longest"), F.sum("val").alias("val"))


def support_agreement(spark: SparkSession, sf: str) -> DataFrame:
    """Sizes of what all workers' top-k share, of what any has, and of what the dense top-k has that no worker sent."""
    top, best = compressors.local_topk(_tokens(spark, sf), K), compressors.exact_topk(_tokens(spark, sf), K).select("coord")
    shared = top.where("worker = 0").select("coord")
    for w in range(1, 5):
        shared = shared.intersect(top.where(F.col("worker") == w).select("coord"))
    sizes = {"all": shared, "any": top.select("coord").distinct(), "missed": best.exceptAll(top.select("coord").distinct())}
    out = None
    for name, coords in sizes.items():
        one = coords.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("part"), "n")
        out = one if out is None else out.unionByName(one)
    return out


def merged_maps(spark: SparkSession, sf: str) -> DataFrame:
    """Two workers' top-k messages added as maps and cut to k again: one merge of tree-top-k in one row."""
    v = sparse.to_map(compressors.local_topk(_tokens(spark, sf), K).where("worker < 2"))
    a, b = v.where("worker = 0").select(F.col("vec").alias("a")), v.where("worker = 1").select(F.col("vec").alias("b"))
    return sparse.from_map(a.crossJoin(b).select(sparse.top(sparse.add(F.col("a"), F.col("b")), K).alias("vec")))


def token_quantized(spark: SparkSession, sf: str) -> DataFrame:
    return compressors.quantize(_tokens(spark, sf), 8).select("worker", "coord", "level")


def counted_ledger(spark: SparkSession, sf: str) -> DataFrame:
    return topology.counted_ledger(sk.build(tables.part_vector(spark, sf, 5, summed=False), SPEC), 5).select("round", "messages", F.col("values").cast("long").alias("values"))


#: Numbers in the small problem's weights, and how many a step keeps.
SMALL_D, SMALL_K = tables.CLASSES * (tables.COMPONENTS + 1), 65


def _first_step(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    """The whole gradient at weight 0 in whole numbers, and the step that four workers make of it."""
    coords = gradients.softmax_gradient_at_zero(spark, sf)
    return coords, sketch_step(coords, SPEC, d=SMALL_D, k=SMALL_K, workers=4, seed=SEED, step=STEP)


def training_step(spark: SparkSession, sf: str) -> DataFrame:
    """The weights after one exact step from 0, in the gradient's unit: gradient, sketch, tree, recovery, exact values, update."""
    _, step = _first_step(spark, sf)
    weights = sk.dimension(spark, SMALL_D).withColumn("w", F.lit(0.0))
    return apply_update(weights, step, 1.0, combine="sum").select("coord", F.col("w").cast("long").alias("w"))


def training_residual(spark: SparkSession, sf: str) -> DataFrame:
    """What each worker carries over to the next step."""
    return residual(*_first_step(spark, sf))


def queries() -> dict[str, Query]:
    def step(**options) -> Query:
        return lambda spark, sf: sketch_step(_tokens(spark, sf), SPEC, d=D, k=K, workers=5, seed=SEED, step=STEP, **options)

    return {
        "shard_vector": tables.part_vector,
        "sketch_sizes": sketch_sizes,
        "sketch_cells": lambda spark, sf: sk.build(tables.part_vector(spark, sf, summed=False), SPEC),
        "sketch_cells_cents": lambda spark, sf: sk.build(tables.price_vector(spark, sf, summed=False), SPEC),
        "sketch_blocks": sketch_blocks,
        "sketch_sql": sketch_sql,
        "sketch_merge_flat": lambda spark, sf: sk.merge_flat(sk.build(tables.part_vector(spark, sf, summed=False), SPEC)),
        "sketch_merge_tree_p4": _tree(4),
        "sketch_merge_tree_p5": _tree(5),
        "sketch_merge_tree_p7": _tree(7),
        "sketch_merge_tree_p8": _tree(8),
        "sketch_subtract": sketch_subtract,
        "sketch_scale": lambda spark, sf: sk.scale(sk.build(tables.part_vector(spark, sf, summed=False), SPEC), -3),
        "sketch_norm": sketch_norm,
        "point_query": point_query,
        "point_query_blocks": _token_estimates,
        "heavy_split": _token_split,
        "heavy_split_signed": lambda spark, sf: recovery.split_heavy(_token_estimates(spark, sf), sk.l2_squared(_merged_tokens(spark, sf), SPEC), K, literal_signed=True),
        "random_fill": lambda spark, sf: recovery.random_fill(_token_split(spark, sf), K, SEED, STEP),
        "recover_heavy_random": _token_support,
        "recover_top_estimate": lambda spark, sf: recovery.top_estimate(_token_estimates(spark, sf), K),
        "recover_heavy_only": lambda spark, sf: recovery.heavy_only(_token_split(spark, sf), K),
        "exact_round": lambda spark, sf: recovery.exact_values(_tokens(spark, sf), _token_support(spark, sf)),
        "tree_sketch_step": step(),
        "star_sketch_step": step(topology_kind="star"),
        "tree_sketch_step_top_estimate": step(recover="top_estimate"),
        "tree_sketch_step_estimates": step(exact=False),
        "dense_sum": lambda spark, sf: compressors.dense_sum(tables.part_vector(spark, sf)),
        "dense_tree_p5": tree_dense,
        "local_topk": lambda spark, sf: compressors.local_topk(_tokens(spark, sf), K),
        "star_topk_step": lambda spark, sf: compressors.star_topk(_tokens(spark, sf), K),
        "tree_topk_step_p4": lambda spark, sf: compressors.tree_topk(_tokens(spark, sf, 4), K, 4),
        "tree_topk_step_p5": lambda spark, sf: compressors.tree_topk(_tokens(spark, sf), K, 5),
        "exact_topk": lambda spark, sf: compressors.exact_topk(tables.part_vector(spark, sf), K),
        "random_k": lambda spark, sf: compressors.random_k(tables.part_vector(spark, sf), K, SEED, STEP),
        "quantize": token_quantized,
        "support_agreement": support_agreement,
        "merged_maps": merged_maps,
        "builtin_top_k": lambda spark, sf: compressors.builtin_top(tables.read_table(spark, sf, "events").select("event_type"), "event_type", 5),
        "event_property_vector": tables.property_vector,
        "tree_edges": _edges,
        "tree_ledger": lambda spark, sf: _ledgers(spark, sf).groupBy("workers", "method", "phase", "direction").agg(F.max("round").alias("rounds"), F.sum("messages").alias("messages"), F.sum("values").alias("values")),
        "counted_ledger": counted_ledger,
        "literal_stride_coverage": lambda spark, sf: topology.literal_stride_coverage(spark, TREE_SIZES, tables.lines_by_worker(spark, sf, TREE_SIZES)),
        "cost_grid": lambda spark, sf: cost.grid(spark, dims=tables.vector_sizes(spark, sf), **GRID),
        "cost_speedup": cost_speedup,
        "compression_ratio": compression,
        "warmup_schedule": warmup_days,
        "minibatch": minibatch,
        "shard_counts": shard_counts,
        "planted_label": tables.planted_labels,
        "softmax_gradient": gradients.softmax_gradient_at_zero,
        "linear_gradient": gradients.linear_gradient_at_zero,
        "training_step": training_step,
        "training_residual": training_residual,
        "estimate_error": estimate_error,
        "heavy_recall": heavy_recall,
        "support_overlap": support_overlap,
        "captured_energy": captured_energy,
        "ledger_rollup": ledger_rollup,
        "speedup_table": speedup_table,
        "token_counts": _tokens,
        "event_user_vector": tables.event_vector,
        "event_daily_sketch": lambda spark, sf: daily.daily_sketch(tables.read_table(spark, sf, "events"), SPEC),
        "event_session_counts": event_session_counts,
        "stream_daily_sketch": lambda spark, sf: daily.stream_daily_sketch(spark, f"{sf}/events.parquet", SPEC),
    }
