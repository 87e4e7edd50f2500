"""The experiments: convergence, time split, sensitivity to k, throughput, scaling, ablations.

Each is a set of ``TrainSpec`` that share rate, batch, steps and seed; what is
compared by accuracy runs in shared jobs, what is compared by time runs alone.
Accuracy never stands without the values sent, measured times never without the
modelled ones: one machine without a network cannot show what a slow link costs.
"""

from __future__ import annotations

import time
from dataclasses import replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from treesketch.functions import cost
from treesketch.functions.hashing import SketchSpec
from treesketch.learning.blocks import LANGUAGES, embedding_blocks, language_blocks
from treesketch.learning.gradients import Perceptron, Softmax
from treesketch.learning.trainer import METHODS, TrainResult, TrainSpec, mini_batches, train, train_all
from treesketch.operators import measures
from treesketch.sources.tables import CLASSES, COMPONENTS

#: Steps of the registered runs; ten (small) or five (large) make an epoch.
SMALL_STEPS, LARGE_STEPS = 100, 40
#: Steps of each run in ``timed``, for trials; none: those of the registered runs.
TIMED_STEPS: int | None = None
SMALL = TrainSpec(model=Softmax(COMPONENTS, CLASSES), steps=20, batch=64, rate=20.0, k=65, sketch=SketchSpec(5, 128, 7))
SMALL_HIDDEN = replace(SMALL, model=Perceptron(COMPONENTS, 128, CLASSES), rate=1.0, k=961, sketch=SketchSpec(5, 512, 7))
#: Buckets of the widest model: a million weights.
WIDE_BUCKETS = 1 << 18
LARGE = TrainSpec(model=Softmax(4096, len(LANGUAGES)), steps=20, batch=32, rate=5.0, k=1024, sketch=SketchSpec(5, 1024, 7))


def small_blocks(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    return embedding_blocks(spark, sf_dir, workers)


def large_blocks(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    return language_blocks(spark, sf_dir, workers, buckets=4096)


def large_blocks_of(buckets: int):
    return lambda spark, sf_dir, workers=4: language_blocks(spark, sf_dir, workers, buckets=buckets)


RUN_SCHEMA = "run string, method string, workers int, k int, width int, step int, epoch int, loss double, acc double, macro double, heavy int, values_sent long, t_compute double, t_compress double, t_comm double, examples_per_s double"


#: What runs that are timed alone have besides.
ALONE_SCHEMA = RUN_SCHEMA + ", t_sample double, t_recover double"


def _lines(name: str, spec: TrainSpec, result: TrainResult, every_step: bool, sample: float | None = None) -> list[tuple]:
    """``sample`` is a step's share of the time for choosing the mini-batches, where it was taken."""
    lines, values, seen = [], 0, []
    for t in result.trace:
        values += t["values"]
        seen.append(t)
        if every_step or t is result.trace[-1]:
            timed = seen[1:] or seen  # the first step warms up
            lines.append((
                name, spec.method, spec.workers, spec.k, spec.sketch.width, t["step"], t["epoch"], t["loss"], t["acc"], t["macro"], t["heavy"], values,
                *(sum(x[c] for x in timed) / len(timed) for c in ("t_compute", "t_compress", "t_comm")), sum(x["examples"] for x in timed) / sum(x["seconds"] + (sample or 0.0) for x in timed),
                *(() if sample is None else (sample, sum(x["t_recover"] for x in timed) / len(timed))),
            ))
    return lines


def report(spark: SparkSession, blocks: DataFrame, specs: dict[str, TrainSpec], *, every_step: bool = False, alone: bool = False) -> DataFrame:
    """One row per run (or per step): name, method, sizes, loss, accuracy, values sent so far, mean times of a step, examples a second.

    Runs share their jobs unless they run ``alone``, one after the other, as times of a method need;
    these share their mini-batches, so they agree in workers, batch, seed and steps. A step of each of
    them has its share of the time for choosing these, ``t_sample``, in its examples a second. Cached blocks stay so.
    """
    kept = blocks.is_cached
    blocks = blocks if kept else blocks.persist()
    sample = None
    if alone:
        one = next(iter(specs.values()))
        blocks.count()  # making the examples is no part of a step
        began = time.perf_counter()
        chosen = mini_batches(blocks, one.workers, one.batch, one.seed, one.steps)
        chosen.count()
        sample = (time.perf_counter() - began) / one.steps
        results = {n: train(blocks, s, chosen) for n, s in specs.items()}
        chosen.unpersist()
    else:
        results = train_all(blocks, specs)
    if not kept:
        blocks.unpersist()
    return spark.createDataFrame([line for n, s in specs.items() for line in _lines(n, s, results[n], every_step, sample)], ALONE_SCHEMA if alone else RUN_SCHEMA)


_KEPT: dict[tuple, list] = {}


def once(name: str, spark: SparkSession, sf_dir: str, make) -> DataFrame:
    """The rows of an experiment, a few thousand at most, kept for the other queries of this process that read them."""
    key = (name, spark.sparkContext.applicationId, sf_dir)
    if key not in _KEPT:
        df = make()
        _KEPT[key] = [df.collect(), df.schema]
    return spark.createDataFrame(*_KEPT[key])


def methods(spec: TrainSpec, names: tuple[str, ...] = METHODS) -> dict[str, TrainSpec]:
    return {m: replace(spec, method=m) for m in names}


def k_sweep(spec: TrainSpec, ks: list[int]) -> dict[str, TrainSpec]:
    return {f"{m}_k{k}": replace(spec, method=m, k=k) for k in ks for m in ("tree_topk", "tree_sketch")}


def ablations(spec: TrainSpec) -> dict[str, TrainSpec]:
    """Recovery, heavy test, residual and second exchange, one at a time."""
    return {
        "as_proposed": spec, "top_estimate": replace(spec, recover="top_estimate"), "heavy_only": replace(spec, recover="heavy_only"), "signed_test": replace(spec, literal_signed=True),
        "no_residual": replace(spec, residual="none"), "estimates": replace(spec, exact=False), "warm_up": replace(spec, warmup=True, steps_per_epoch=4), "summed": replace(spec, combine="sum", rate=spec.rate / spec.workers),
    }


def equal_volume(spec: TrainSpec) -> dict[str, TrainSpec]:
    """Tree-top-k with as many values a message as the sketch and its exact round."""
    matched = max(1, (spec.sketch.size + spec.k) // 2)
    return {"tree_sketch": replace(spec, method="tree_sketch"), "top_estimate": replace(spec, method="tree_sketch", recover="top_estimate"), "tree_topk_same_k": replace(spec, method="tree_topk"), "tree_topk_same_volume": replace(spec, method="tree_topk", k=matched)}


#: The methods that are compared at each size, those whose rates and parts of a step are taken, and modelled links: start-up and time for a value of eight bytes at 1 Gbps, in seconds; 10^4 between them.
COMPARED = ("tree_topk", "star_sketch", "tree_sketch")
TIMED = METHODS
BETA = 8 * 8 / 1e9
ALPHA = 1e4 * BETA


def convergence(steps: DataFrame, tolerance: float = 0.02) -> DataFrame:
    """Per method and epoch: mean loss, last accuracy, values sent, and the epoch from which the method's accuracy stays within ``tolerance`` of its last."""
    curves = measures.curve(steps)
    sent = steps.groupBy("method", "epoch").agg(F.max("values_sent").alias("values_sent"))
    settled = measures.epochs_to_converge(curves, tolerance).withColumnRenamed("epoch", "settled")
    return curves.join(sent, ["method", "epoch"]).join(settled, "method", "left")


def modelled(rows: DataFrame, d: int, size: int) -> DataFrame:
    """Adds ``t_modelled``, the exchange's time by the cost model on the links above."""
    args = {"workers": F.col("workers"), "d": F.lit(float(d)), "k": F.col("k"), "size": F.lit(float(size)), "alpha": F.lit(ALPHA), "beta": F.lit(BETA)}
    each = F.lit(None).cast("double")
    for m in METHODS:
        each = F.when(F.col("method") == m, cost.predict(m, **args).cast("double")).otherwise(each)
    return rows.withColumn("t_modelled", each)


def modelled_step() -> Column:
    """The time of a step with the modelled exchange: gradient, compression, recovery and update as measured, without Spark's jobs and the choice of mini-batches."""
    return F.col("t_compute") + F.col("t_compress") + F.col("t_recover") + F.col("t_modelled")


def timed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each method alone, all steps of the small and of the large run."""
    out = None
    for model, spec, make, steps in (("small", SMALL, small_blocks, SMALL_STEPS), ("large", LARGE, large_blocks, LARGE_STEPS)):
        steps = steps if TIMED_STEPS is None else TIMED_STEPS
        spec = replace(spec, steps=steps, evaluate_every=steps)
        rows = report(spark, make(spark, sf_dir), methods(spec, TIMED), alone=True)
        rows = modelled(rows, spec.model.size, spec.sketch.size).withColumn("model", F.lit(model))
        out = rows if out is None else out.unionByName(rows)
    return out


def time_split(rows: DataFrame) -> DataFrame:
    """Per model and method the parts of a step, measured, and the share of communication measured and with the modelled exchange."""
    work = F.col("t_compute") + F.col("t_compress")
    shares = None
    for model in ("small", "large"):
        one = measures.comm_share(rows.where(F.col("model") == model)).withColumn("model", F.lit(model))
        shares = one if shares is None else shares.unionByName(one)
    parts = rows.select("model", "method", "t_compute", "t_compress", "t_comm", "t_modelled", (F.col("t_modelled") / (work + F.col("t_modelled"))).alias("modelled_share"))
    return parts.join(shares, ["model", "method"])


def throughput(rows: DataFrame, spec_batch: dict[str, int]) -> DataFrame:
    """Per model and method examples a second, measured and with the modelled exchange, and the speed-up of tree-sketch over it both ways; the mean over models too."""
    batch = F.lit(None).cast("double")
    for model, n in spec_batch.items():
        batch = F.when(F.col("model") == model, F.lit(float(n))).otherwise(batch)
    rates = rows.select("model", "method", "examples_per_s", (F.col("workers") * batch / modelled_step()).alias("modelled_per_s"))
    out = rates
    for column, name in (("examples_per_s", "speedup"), ("modelled_per_s", "modelled_speedup")):
        ratios = None
        for over in (m for m in TIMED if m != "tree_sketch"):
            one = measures.speedup(rates.select("model", "method", F.col(column).alias("examples_per_s")), "tree_sketch", over)
            ratios = one if ratios is None else ratios.unionByName(one)
        mean = measures.mean_speedup(ratios).select(F.col("over").alias("method"), F.col("mean_speedup").alias(f"mean_{name}"))
        out = out.join(ratios.select("model", F.col("over").alias("method"), F.col("speedup").alias(name)), ["model", "method"], "left").join(mean, "method", "left")
    return out


def scaling(spark: SparkSession, sf_dir: str, counts: list[int], spec: TrainSpec = LARGE, names: tuple[str, ...] = COMPARED) -> DataFrame:
    """For each number of workers with the same batch each: examples a second and efficiency, measured and with the modelled exchange.

    Each method runs alone, so its efficiency is its own.
    """
    out, blocks = None, large_blocks(spark, sf_dir, 0).persist()  # one table of bags, dealt out anew for each number of workers
    for p in counts:
        runs = {f"{m}_p{p}": replace(spec, method=m, workers=p) for m in names}
        one = modelled(report(spark, blocks, runs, alone=True), spec.model.size, spec.sketch.size)
        out = one if out is None else out.unionByName(one)
    blocks.unpersist()
    rates = out.select("method", "workers", "examples_per_s", (F.col("workers") * spec.batch / modelled_step()).alias("modelled_per_s"), "t_comm", "t_modelled")
    found = rates
    for column, name in (("examples_per_s", "efficiency"), ("modelled_per_s", "modelled_efficiency")):
        one = measures.scaling_efficiency(rates.select("method", "workers", F.col(column).alias("examples_per_s"))).withColumnRenamed("efficiency", name)
        found = found.join(one, ["method", "workers"])
    return found


#: The grids of the sensitivity and scaling experiments.
SMALL_KS, LARGE_KS, WORKERS = [4, 16, 65, 162], [64, 256, 1024, 4096], [1, 2, 4, 5, 6, 7, 8]


def queries() -> dict:
    """The experiments on the given tables, each a whole run of its steps."""
    small = replace(SMALL, steps=SMALL_STEPS, steps_per_epoch=10, evaluate_every=10)
    large = replace(LARGE, steps=LARGE_STEPS, steps_per_epoch=5, evaluate_every=5)
    hidden = replace(SMALL_HIDDEN, steps=LARGE_STEPS, steps_per_epoch=10, evaluate_every=10)
    wide = replace(LARGE, model=Softmax(WIDE_BUCKETS, len(LANGUAGES)), steps=4, steps_per_epoch=2, evaluate_every=2, k=10_000, sketch=SketchSpec(5, 4096, 7))
    traces = {
        "train_small": (small, small_blocks, METHODS), "train_large": (large, large_blocks, METHODS), "train_hidden": (hidden, small_blocks, COMPARED),
        "train_wide": (wide, large_blocks_of(WIDE_BUCKETS), ("tree_sketch", "tree_topk")),
    }
    out = {}
    for name, (spec, make, names) in traces.items():
        trace = lambda spark, sf, name=name, spec=spec, make=make, names=names: once(name, spark, sf, lambda: report(spark, make(spark, sf), methods(spec, names), every_step=True))
        out[name] = trace
        out[name.replace("train", "convergence")] = lambda spark, sf, trace=trace: convergence(trace(spark, sf))
    times = lambda spark, sf: once("timed", spark, sf, lambda: timed(spark, sf))
    out["time_split"] = lambda spark, sf: time_split(times(spark, sf))
    out["throughput"] = lambda spark, sf: throughput(times(spark, sf), {"small": SMALL.batch, "large": LARGE.batch})
    out["k_sweep"] = lambda spark, sf: report(spark, small_blocks(spark, sf), k_sweep(small, SMALL_KS))
    out["k_sweep_large"] = lambda spark, sf: report(spark, large_blocks(spark, sf), k_sweep(large, LARGE_KS))
    out["ablations"] = lambda spark, sf: report(spark, small_blocks(spark, sf), ablations(small))
    out["equal_volume"] = lambda spark, sf: report(spark, small_blocks(spark, sf), equal_volume(small))
    out["scaling"] = lambda spark, sf: scaling(spark, sf, WORKERS, replace(LARGE, steps=LARGE_STEPS, evaluate_every=LARGE_STEPS))
    return out
