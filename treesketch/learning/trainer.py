"""Synchronous data-parallel training with every method of exchange.

The mini-batches of all steps are chosen in two passes over the examples before
the first step, and stay in memory. A step is three small jobs. The first takes
each worker's mini-batch, computes the gradient and adds what earlier steps left unsent; the workers' vectors go
through the shared checkpoint folder and are deleted a step later. The second
merges the compressed vectors along the method's topology; what comes to the
driver is the merged message. The third fetches the exact values on the
support. So what a step shuffles depends on batch, workers and message, not on
the number of examples. Batches and hashes depend on keys and step alone, and a
lost executor's part is recomputed to the same values.

Several runs on the same examples, workers and batches share their jobs; a run
is a key beside the worker.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treesketch.functions.hashing import SketchSpec, np_fill_order
from treesketch.learning.blocks import Block, dealt, joined
from treesketch.learning.schedule import schedule_at
from treesketch.operators.topology import ledger_lines, rounds
from treesketch.sources import scratch

METHODS = ("dense", "star_topk", "tree_topk", "star_sketch", "tree_sketch")
#: Numbers in all workers' vectors together that the array path allows (1 GB); larger models use ``plans.steps`` on frames.
MAX_STATE = 1 << 27


@dataclass(frozen=True)
class TrainSpec:
    model: object
    method: str = "tree_sketch"
    workers: int = 4
    steps: int = 60
    batch: int = 64
    rate: float = 1.0
    k: int = 100
    sketch: SketchSpec = field(default_factory=SketchSpec)
    recover: str = "heavy_random"
    residual: str = "local"
    combine: str = "mean"
    exact: bool = True
    literal_signed: bool = False
    warmup: bool = False
    steps_per_epoch: int = 10
    momentum: float = 0.0
    seed: int = 1
    evaluate_every: int = 10
    patience: int = 0

    def __post_init__(self):
        if self.method not in METHODS:
            raise ValueError(f"method is one of {METHODS}")
        if self.residual not in ("none", "local") or self.combine not in ("mean", "sum"):
            raise ValueError("residual is 'none' or 'local', combine 'mean' or 'sum'")
        if self.k < 1 or self.workers < 1:
            raise ValueError("k and workers must be positive")
        if self.model.size * self.workers > MAX_STATE:
            raise ValueError("too large for array weights; use plans.steps.method_step and apply_update on frames")


@dataclass
class TrainResult:
    weights: np.ndarray
    trace: list[dict]
    ledger: list[tuple]

    def trace_frame(self, spark) -> DataFrame:
        return spark.createDataFrame(self.trace)


def np_top(values: np.ndarray, k: int) -> np.ndarray:
    """The k coordinates of largest magnitude, ties to the smaller; zeros are not sent."""
    k = min(k, int(np.count_nonzero(values)))
    return np.sort(np.lexsort((np.arange(len(values)), -np.abs(values)))[:k])


def np_sketch(values: np.ndarray, spec: SketchSpec, buckets: np.ndarray, signs: np.ndarray) -> np.ndarray:
    return np.concatenate([np.bincount(buckets[r], signs[r] * values, spec.width) for r in range(spec.rows)])


def np_recover(cells: np.ndarray, spec: SketchSpec, d: int, k: int, how: str, seed: int, step: int, literal_signed: bool = False) -> tuple[np.ndarray, np.ndarray, int]:
    """(support, estimates on it, heavy coordinates) of summed cells: the NumPy twin of ``operators.recovery``."""
    coord = np.arange(d)
    buckets, signs = spec.np_buckets(coord), spec.np_signs(coord)
    table = cells.reshape(spec.rows, spec.width)
    est = np.sort(signs * np.take_along_axis(table, buckets, 1), axis=0)[spec.rows // 2]
    if how == "top_estimate":
        support = np.lexsort((coord, -np.abs(est)))[: min(k, d)]
        return np.sort(support), est[np.sort(support)], len(support)
    l2 = np.sort((table * table).sum(1))[spec.rows // 2]
    heavy = (est * k if literal_signed else est * est * k) >= l2
    light = np.where(heavy, 0, np_fill_order(coord, seed, step))
    order = np.lexsort((coord, light, np.where(heavy, -np.abs(est), 0.0), ~heavy))
    support = np.sort(order[: min(k, d)] if how == "heavy_random" else order[: min(k, int(heavy.sum()))])
    return support, est[support], int(min(heavy.sum(), k))


BLOCK_COLUMNS = ("worker", "n", "keys", "labels", "index", "value", "starts")
CHOSEN = pa.schema([("step", pa.int32()), ("worker", pa.int32()), ("n", pa.int32()), *[(c, pa.binary()) for c in BLOCK_COLUMNS[2:]]])
LOCAL_SCHEMA = "run string, worker int, loss double, seconds double, compress_seconds double, u binary, at binary, message binary"
MESSAGE_SCHEMA = "run string, worker int, child int, loss double, seconds double, compress_seconds double, n long, at binary, message binary"


def place(blocks: DataFrame, workers: int) -> DataFrame:
    """The training blocks by worker, in several parts of a worker where there are the cores for it; kept in memory or on disk."""
    parts = max(1, blocks.sparkSession.sparkContext.defaultParallelism // workers)
    rows = blocks.where(~F.col("held_out")).select(*BLOCK_COLUMNS)
    return rows.repartition(workers * parts, "worker", F.pmod(F.xxhash64("keys"), F.lit(parts))).persist(StorageLevel.MEMORY_AND_DISK)


def _first(block: Block, batch: int, seed: int, step: int) -> dict:
    """The ``batch`` examples of a block that the shared order of the step puts first."""
    order = np_fill_order(block.keys, seed, step)
    take = np.argpartition(order, batch - 1)[:batch] if len(order) > batch else np.arange(len(order))
    return block.some(np.sort(take))


def _minibatch(placed: DataFrame, batch: int, seed: int, step: int) -> DataFrame:
    """For each worker and task at most ``batch`` examples that can be in the worker's mini-batch; no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, dict] = {}
        for rows in batches:
            for row in rows.to_pylist():
                worker, now = row.pop("worker"), _first(Block(row), batch, seed, step)
                held[worker] = _first(Block(joined([held[worker], now])), batch, seed, step) if worker in held else now
        for worker, row in sorted(held.items()):
            yield pa.RecordBatch.from_arrays([pa.array([worker], pa.int32()), pa.array([row["n"]], pa.int32()), *[pa.array([row[c]], pa.binary()) for c in BLOCK_COLUMNS[2:]]], names=list(BLOCK_COLUMNS))

    return placed.mapInArrow(run, "worker int, n int, keys binary, labels binary, index binary, value binary, starts binary")


def mini_batches(blocks: DataFrame, workers: int, batch: int, seed: int, steps: int) -> DataFrame:
    """``step`` and a block for each step and worker: all mini-batches of a run, as ``_first`` has them, kept in memory or on disk.

    A pass over the keys finds how far each step's mini-batch reaches in the
    shared order, a second takes the examples up to there. So examples are read
    twice whatever the number of steps, and what is shuffled and kept goes with
    steps, workers and batch.
    """
    rows = blocks.where(~F.col("held_out"))
    none = np.iinfo(np.int64).max

    def least(orders: np.ndarray) -> np.ndarray:
        return np.partition(orders, batch - 1, axis=1)[:, :batch] if orders.shape[1] > batch else orders

    def reach(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}
        for part in batches:
            for own, raw in zip(part.column(0).to_pylist(), part.column(1)):
                keys = np.frombuffer(raw.as_buffer(), np.int64)
                of = dealt(keys, own, workers)
                for worker in np.unique(of).tolist():
                    here = keys[of == worker]
                    now = least(np.stack([np_fill_order(here, seed, step) for step in range(1, steps + 1)]))
                    held[worker] = least(np.concatenate([held[worker], now], axis=1)) if worker in held else now
        for worker, orders in sorted(held.items()):
            yield pa.RecordBatch.from_arrays([pa.array([worker], pa.int32()), pa.array([np.ascontiguousarray(orders).tobytes()], pa.binary())], names=["worker", "orders"])

    def merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}
        for part in batches:
            for worker, raw in zip(*(part.column(i).to_pylist() for i in (0, 1))):
                now = np.frombuffer(raw, np.int64).reshape(steps, -1)
                held[worker] = least(np.concatenate([held[worker], now], axis=1)) if worker in held else now
        for worker, orders in sorted(held.items()):
            limit = orders.max(1) if orders.shape[1] >= batch else np.full(steps, none)
            yield pa.RecordBatch.from_arrays([pa.array([worker], pa.int32()), pa.array([limit.tobytes()], pa.binary())], names=["worker", "limits"])

    found = rows.select("worker", "keys").mapInArrow(reach, "worker int, orders binary").repartition(workers, "worker").mapInArrow(merged, "worker int, limits binary").collect()
    limits = blocks.sparkSession.sparkContext.broadcast({r["worker"]: np.frombuffer(r["limits"], np.int64) for r in found})

    def taken(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = limits.value
        for part in batches:
            for row in part.to_pylist():
                block = Block(row)
                of = dealt(block.keys, row["worker"], workers)
                for worker in np.unique(of).tolist():
                    here = np.flatnonzero(of == worker)
                    out = []
                    for step in range(1, steps + 1):
                        take = here[np_fill_order(block.keys[here], seed, step) <= known[worker][step - 1]]
                        if len(take):
                            out.append({"step": step, "worker": worker} | block.some(take))
                    if out:
                        yield pa.RecordBatch.from_pylist(out, CHOSEN)

    def joined_by_step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, parts = None, []

        def made() -> pa.RecordBatch:
            block = Block(_first(Block(joined(parts)), batch, seed, at[0]))
            return pa.RecordBatch.from_pylist([{"step": at[0], "worker": at[1]} | block.some(np.argsort(block.keys, kind="stable"))], CHOSEN)

        for part in batches:
            for row in part.to_pylist():
                if (row["step"], row["worker"]) != at:
                    if parts:
                        yield made()
                    at, parts = (row["step"], row["worker"]), []
                parts.append(row)
        if parts:
            yield made()

    schema = "step int, worker int, n int, keys binary, labels binary, index binary, value binary, starts binary"
    parts = rows.select(*BLOCK_COLUMNS).mapInArrow(taken, schema).repartition(blocks.sparkSession.sparkContext.defaultParallelism, "step", "worker")
    return parts.sortWithinPartitions("step", "worker").mapInArrow(joined_by_step, schema).persist(StorageLevel.MEMORY_AND_DISK)


def _unsent(u: np.ndarray, sent: dict) -> np.ndarray:
    """What a worker's last vector still owes: all but what the last step delivered of it, by the k of that step."""
    rest = u.copy()
    rest[sent["support"] if sent["k"] is None else np.intersect1d(np_top(u, sent["k"]), sent["support"])] = 0.0
    return rest


def _compress(u: np.ndarray, spec: TrainSpec, k: int) -> tuple[bytes | None, bytes]:
    """A worker's message: coordinates (none for a whole vector or a sketch) and values."""
    if spec.method.endswith("sketch"):
        coord = np.arange(len(u))
        return None, np_sketch(u, spec.sketch, spec.sketch.np_buckets(coord), spec.sketch.np_signs(coord)).tobytes()
    if spec.method == "dense":
        return None, u.tobytes()
    top = np_top(u, k)
    return top.astype("<i4").tobytes(), u[top].tobytes()


def _local_vectors(placed: DataFrame, state: DataFrame | None, specs: dict[str, TrainSpec], now: dict[str, dict], step: int) -> DataFrame:
    """A row of ``LOCAL_SCHEMA`` for each run and worker, with u = gradient + what was left unsent.

    ``now`` has the weights, the k and what was last sent of each run.
    """
    one = next(iter(specs.values()))
    known = placed.sparkSession.sparkContext.broadcast(now)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        runs = known.value
        parts: dict[int, list[dict]] = {}
        left: dict[tuple[str, int], np.ndarray] = {}
        for batch in batches:
            for row in batch.to_pylist():
                if row["u"] is not None:
                    left[row["run"], row["worker"]] = np.frombuffer(row["u"])
                else:
                    parts.setdefault(row["worker"], []).append(row)
        for worker in sorted(parts):
            block = Block(_first(Block(joined(parts[worker])), one.batch, one.seed, step))
            x = block.rows(one.model.features)
            for name, spec in specs.items():
                began = time.perf_counter()
                u, loss = spec.model.gradient(runs[name]["weights"], x, block.labels)
                compute, began = time.perf_counter() - began, time.perf_counter()
                if spec.residual == "local" and (name, worker) in left and runs[name]["sent"] is not None:
                    u = u + _unsent(left[name, worker], runs[name]["sent"])
                at, message = _compress(u, spec, runs[name]["k"])
                yield pa.RecordBatch.from_arrays(
                    [pa.array([name]), pa.array([worker], pa.int32()), pa.array([loss]), pa.array([compute]), pa.array([time.perf_counter() - began]), pa.array([u.tobytes()], pa.binary()), pa.array([at], pa.binary()), pa.array([message], pa.binary())],
                    names=["run", "worker", "loss", "seconds", "compress_seconds", "u", "at", "message"],
                )

    rows = _minibatch(placed, one.batch, one.seed, step).select(F.lit(None).cast("string").alias("run"), *BLOCK_COLUMNS, F.lit(None).cast("binary").alias("u"))
    if state is not None:
        nothing = [F.lit(None).cast("int").alias("n"), *[F.lit(None).cast("binary").alias(c) for c in BLOCK_COLUMNS[2:]]]
        rows = rows.unionByName(state.select("run", "worker", *nothing, "u"))
    return rows.repartition(one.workers, "worker").mapInArrow(run, LOCAL_SCHEMA)


class _Sum:
    """The sum of messages: values with coordinates, or plain arrays."""

    def __init__(self, at: bytes | None, message: bytes):
        self.at = None if at is None else np.frombuffer(at, "<i4").astype(np.int64)
        self.values = np.frombuffer(message)

    def add(self, other: _Sum) -> None:
        if self.at is None:
            self.values = self.values + other.values
            return
        both, place = np.unique(np.concatenate([self.at, other.at]), return_inverse=True)
        values = np.zeros(len(both))
        values[place[: len(self.at)]] = self.values
        values[place[len(self.at) :]] += other.values
        self.at, self.values = both, values

    def cut(self, k: int) -> None:
        top = np_top(self.values, k)
        self.at, self.values = self.at[top], self.values[top]


def _merge(local: DataFrame, specs: dict[str, TrainSpec], ks: dict[str, int]) -> dict[str, tuple]:
    """(sum, mean loss, longest gradient, longest compression, workers) of each run.

    Rounds of pairwise sums in the trees, one sum at the star; cut to k after
    each merge in the tree of top-k.
    """
    workers = next(iter(specs.values())).workers
    stars = [n for n, s in specs.items() if s.method.startswith("star")]
    cuts = {n: ks[n] for n, s in specs.items() if s.method == "tree_topk"}

    def summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, total, facts = None, None, None

        def made() -> pa.RecordBatch:
            if at[0] in cuts:
                total.cut(cuts[at[0]])
            where = None if total.at is None else total.at.astype("<i4").tobytes()
            values = [[at[0]], [at[1]], [at[1]], *[[f] for f in facts], [where], [total.values.tobytes()]]
            return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(values, types)], names=names)

        for batch in batches:
            for run, worker, _, loss, seconds, compress, n, where, message in zip(*(batch.column(i).to_pylist() for i in range(9))):
                if (run, worker) == at:
                    total.add(_Sum(where, message))
                    facts = [facts[0] + loss, max(facts[1], seconds), max(facts[2], compress), facts[3] + n]
                    continue
                if at is not None:
                    yield made()
                at, total, facts = (run, worker), _Sum(where, message), [loss, seconds, compress, n]
        if at is not None:
            yield made()

    names = ["run", "worker", "child", "loss", "seconds", "compress_seconds", "n", "at", "message"]
    types = (pa.string(), pa.int32(), pa.int32(), pa.float64(), pa.float64(), pa.float64(), pa.int64(), pa.binary(), pa.binary())
    now = local.select("run", "worker", "loss", "seconds", "compress_seconds", F.lit(1).cast("long").alias("n"), "at", "message")
    cores = local.sparkSession.sparkContext.defaultParallelism
    for i in range(max(1, rounds(workers) if len(stars) < len(specs) else 1)):
        to = F.when(F.col("run").isin(stars), F.lit(0)).otherwise(F.shiftright("worker", 1)) if stars else F.shiftright("worker", 1)
        dealt = now.select("run", to.cast("int").alias("worker"), F.col("worker").alias("child"), *names[3:])
        parts = min(cores, len(specs) * max(1, -(-workers >> (i + 1))))
        now = dealt.repartition(parts, "run", "worker").sortWithinPartitions("run", "worker", "child").mapInArrow(summed, MESSAGE_SCHEMA)
    out = {}
    for r in now.collect():
        out[r["run"]] = (_Sum(r["at"], r["message"]), r["loss"] / r["n"], r["seconds"], r["compress_seconds"], r["n"])
    return out


def _exact(local: DataFrame, supports: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
    """Sum over workers of u on each run's support: k numbers from each worker."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, worker, raw in zip(*(batch.column(i).to_pylist() for i in range(3))):
                yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([worker], pa.int32()), pa.array([np.frombuffer(raw)[supports[name]].tobytes()], pa.binary())], names=["run", "worker", "v"])

    rows = local.where(F.col("run").isin(list(supports))).select("run", "worker", "u").mapInArrow(run, "run string, worker int, v binary").collect()
    out = {name: np.zeros(len(s)) for name, s in supports.items()}
    for r in sorted(rows, key=lambda r: (r["run"], r["worker"])):
        out[r["run"]] = out[r["run"]] + np.frombuffer(r["v"])
    return out


def evaluate_all(blocks: DataFrame, model, weights: dict[str, np.ndarray], *, held_out: bool = True) -> dict[str, tuple[float, float]]:
    """(accuracy, mean accuracy over classes) of each run's weights on the held-out or the training blocks, in one pass."""
    known = blocks.sparkSession.sparkContext.broadcast(weights)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hits: dict[tuple[str, int], list[int]] = {}
        for batch in batches:
            for row in batch.to_pylist():
                block = Block(row)
                x = block.rows(model.features)
                for name, w in known.value.items():
                    hit = model.scores(w, x).argmax(1) == block.labels
                    for label in np.unique(block.labels).tolist():
                        count, of = hits.setdefault((name, label), [0, 0]), block.labels == label
                        hits[name, label] = [count[0] + int(hit[of].sum()), count[1] + int(of.sum())]
        if hits:
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in hits]), *[pa.array(c, pa.int64()) for c in ([k[1] for k in hits], *zip(*hits.values()))]], names=["run", "label", "hit", "n"])

    rows = blocks.where(F.col("held_out") == held_out).select("n", "keys", "labels", "index", "value", "starts").mapInArrow(run, "run string, label long, hit long, n long")
    found: dict[str, list] = {name: [] for name in weights}
    for r in rows.groupBy("run", "label").agg(F.sum("hit").alias("hit"), F.sum("n").alias("n")).collect():
        found[r["run"]].append((r["hit"], r["n"]))
    return {name: (sum(h for h, _ in f) / sum(n for _, n in f), float(np.mean([h / n for h, n in f]))) if f else (0.0, 0.0) for name, f in found.items()}


def evaluate(blocks: DataFrame, model, weights: np.ndarray, *, held_out: bool = True) -> tuple[float, float]:
    """(accuracy, mean accuracy over classes) on the held-out or the training blocks."""
    return evaluate_all(blocks, model, {"": weights}, held_out=held_out)[""]


@dataclass
class _Run:
    """What changes from step to step in one run."""

    spec: TrainSpec
    weights: np.ndarray
    velocity: np.ndarray
    sent: dict | None = None
    trace: list[dict] = field(default_factory=list)
    messages: list[tuple] = field(default_factory=list)
    best: float = np.inf
    since: int = 0
    scores: tuple[float, float] = (0.0, 0.0)


def train_all(blocks: DataFrame, specs: dict[str, TrainSpec], chosen: DataFrame | None = None) -> dict[str, TrainResult]:
    """Several runs at once on the same blocks; all share workers, batch, seed, steps, model and the steps between evaluations.

    The times of a step that runs share, its communication, are dealt out
    evenly; for times of a method run it alone. A step's ``seconds`` go from its
    mini-batch to the new weights; ``t_recover`` is the driver's CPU time for one run,
    recovery (its wait is in ``t_comm``) and update. ``blocks`` stays as it is,
    cached or not. ``chosen`` are the runs' ``mini_batches``, where they are known.
    """
    shared = {(s.workers, s.batch, s.seed, s.steps, s.evaluate_every, s.model) for s in specs.values()}
    if len(shared) != 1:
        raise ValueError("runs that share their jobs must agree in workers, batch, seed, steps, evaluate_every and model")
    spark = blocks.sparkSession
    one = next(iter(specs.values()))
    d = one.model.size
    if d * one.workers * len(specs) > MAX_STATE:
        raise ValueError("too many numbers in all runs' vectors; run fewer at once")
    runs = {n: _Run(s, s.model.start(s.seed), np.zeros(d)) for n, s in specs.items()}
    batches = mini_batches(blocks, one.workers, one.batch, one.seed, one.steps) if chosen is None else chosen
    state, old = None, None
    for step in range(1, one.steps + 1):
        active = {n: r for n, r in runs.items() if not (r.spec.patience and r.since >= r.spec.patience)}
        if not active:
            break
        began = time.perf_counter()
        plan = {n: schedule_at((step - 1) // r.spec.steps_per_epoch, d, r.spec.k, r.spec.rate, r.spec.warmup) for n, r in active.items()}
        now = {n: r.spec for n, r in active.items()}
        local = _local_vectors(batches.where(F.col("step") == step).select(*BLOCK_COLUMNS), state, now, {n: {"weights": r.weights, "sent": r.sent, "k": plan[n][0]} for n, r in active.items()}, step)
        local, path = scratch.keep(local, "vectors")
        computed = time.perf_counter() - began
        merged = _merge(local, now, {n: k for n, (k, _) in plan.items()})
        found, wanted, recovered = {}, {}, {}
        for n, r in active.items():
            total, since = merged[n][0], time.thread_time()
            if r.spec.method.endswith("sketch"):
                support, values, heavy = np_recover(total.values, r.spec.sketch, d, plan[n][0], r.spec.recover, r.spec.seed, step, r.spec.literal_signed)
                if r.spec.exact:
                    wanted[n] = support
            else:
                at = np.arange(d) if total.at is None else total.at
                support, values, heavy = at[total.values != 0], total.values[total.values != 0], 0
            found[n] = [support, values, heavy]
            recovered[n] = time.thread_time() - since
        for n, values in (_exact(local, wanted) if wanted else {}).items():
            found[n][1] = values
        if old:
            scratch.drop(spark, old)
        state, old = local, path
        exchanged = time.perf_counter() - began
        for n, r in active.items():
            since = time.thread_time()
            (support, values, heavy), (k, rate), spec = found[n], plan[n], r.spec
            update = np.zeros(d)
            update[support] = values
            r.velocity = spec.momentum * r.velocity + update
            r.weights = r.weights - rate / (spec.workers if spec.combine == "mean" else 1) * r.velocity
            r.sent = {"support": support, "k": k if spec.method.endswith("topk") else None}
            recovered[n] += time.thread_time() - since
        seconds = time.perf_counter() - began
        if step % one.evaluate_every == 0 or step == one.steps:
            for n, scores in evaluate_all(blocks, one.model, {n: r.weights for n, r in active.items()}).items():
                active[n].scores = scores
        for n, r in active.items():
            (support, values, heavy), (k, rate), spec = found[n], plan[n], r.spec
            _, loss, t_compute, t_compress, n_workers = merged[n]
            lines = ledger_lines(spec.method, spec.workers, d=d, k=len(support) if spec.method.endswith("sketch") else k, size=spec.sketch.size, union=len(support) if spec.method == "star_topk" else None)
            r.messages += [(step, *line) for line in lines]
            r.trace.append({
                "step": step, "epoch": (step - 1) // spec.steps_per_epoch, "method": spec.method, "loss": loss, "acc": r.scores[0], "macro": r.scores[1], "k": k, "heavy": heavy, "support": len(support),
                "t_compute": t_compute, "t_compress": t_compress, "t_comm": max(0.0, exchanged - computed) / len(active), "t_recover": recovered[n], "seconds": seconds / len(active), "examples": spec.batch * n_workers, "values": sum(x[5] for x in lines),
            })
            r.best, r.since = (loss, 0) if loss < r.best - 1e-4 else (r.best, r.since + 1)
    if old:
        scratch.drop(spark, old)
    if chosen is None:
        batches.unpersist()
    return {n: TrainResult(r.weights, r.trace, r.messages) for n, r in runs.items()}


def train(blocks: DataFrame, spec: TrainSpec, chosen: DataFrame | None = None) -> TrainResult:
    """Run ``spec.steps`` steps on blocks of examples; see the module for what a step is."""
    return train_all(blocks, {spec.method: spec}, chosen)[spec.method]
