from dataclasses import replace

import numpy as np
import pytest

from treesketch.experiments import runs
from treesketch.functions.hashing import SketchSpec
from treesketch.learning.blocks import embedding_blocks
from treesketch.learning.gradients import Linear, Perceptron, Softmax, logistic
from treesketch.learning.schedule import schedule_at, warmup_schedule
from treesketch.learning.simulate import Problem, simulate
from treesketch.learning.trainer import METHODS, TrainSpec, evaluate, train, train_all

SMALL = replace(runs.SMALL, steps=4, evaluate_every=4, sketch=SketchSpec(5, 256, 7))


@pytest.fixture(scope="module")
def small(spark, tiny):
    return runs.small_blocks(spark, tiny).persist()


@pytest.mark.parametrize("model", [Softmax(3, 4), Perceptron(3, 5, 4), Linear(3), logistic(3)])
def test_gradients_match_differences(model):
    rng = np.random.default_rng(1)
    x, w = rng.standard_normal((6, 3)), rng.standard_normal(model.size)
    y = rng.standard_normal(6) if isinstance(model, Linear) else rng.integers(0, getattr(model, "classes", 2), 6)
    g, _ = model.gradient(w, x, y)
    for i in range(model.size):
        e = np.zeros(model.size)
        e[i] = 1e-6
        assert abs((model.gradient(w + e, x, y)[1] - model.gradient(w - e, x, y)[1]) / 2e-6 - g[i]) < 1e-5


def test_star_and_tree_sketches_train_alike(small):
    a, b = (train(small, replace(SMALL, method=m)) for m in ("tree_sketch", "star_sketch"))
    assert np.allclose(a.weights, b.weights) and a.trace[-1]["values"] < b.trace[-1]["values"]


@pytest.mark.parametrize("method", ["star_topk", "tree_topk", "tree_sketch"])
def test_keeping_everything_is_dense_training(small, method):
    every = replace(SMALL, k=SMALL.model.size, steps=3)
    assert np.allclose(train(small, replace(every, method=method)).weights, train(small, replace(every, method="dense")).weights)


@pytest.mark.parametrize("method", METHODS)
def test_one_process_loop_gives_the_same_run(small, method):
    spec = replace(SMALL, method=method, steps=3)
    a, b = train(small, spec), simulate(Problem(small, 64), spec)
    assert np.allclose(a.weights, b["weights"]) and sum(t["values"] for t in a.trace) == b["values"]


@pytest.mark.parametrize("options", [dict(warmup=True, steps_per_epoch=1, steps=5), dict(momentum=0.5, steps=3)])
def test_runs_that_share_jobs_equal_the_loop(small, options):
    """All five methods at once; under warm-up the k changes with each step."""
    specs = {m: replace(SMALL, method=m, evaluate_every=9, **options) for m in METHODS}
    problem, got = Problem(small, 64), train_all(small, specs)
    for m, spec in specs.items():
        want = simulate(problem, spec)
        assert np.allclose(got[m].weights, want["weights"], rtol=0, atol=1e-12) and sum(t["values"] for t in got[m].trace) == want["values"]
        assert np.allclose([t["loss"] for t in got[m].trace], want["losses"])
    assert small.is_cached


def test_a_step_shuffles_batches_and_messages_only(spark, tiny):
    """Rows that the first job shuffles: one for each worker and task, whatever the number of examples; top-k messages have k numbers."""
    from treesketch.learning import trainer
    from treesketch.plans.rewrites import shuffle_metrics

    blocks = runs.small_blocks(spark, tiny)
    sizes = []
    for copies in (1, 30):
        many = blocks
        for _ in range(copies - 1):
            many = many.unionByName(blocks)
        placed = trainer.place(many, 4)
        placed.count()
        spec = replace(SMALL, method="tree_topk", k=7)
        now = {"a": {"weights": spec.model.start(1), "sent": None, "k": 7}}
        local = trainer._local_vectors(placed, None, {"a": spec}, now, 1).persist()
        assert all(len(r["at"]) == 28 and len(r["message"]) == 56 for r in local.select("at", "message").collect())
        sizes.append(shuffle_metrics(trainer._minibatch(placed, 16, 1, 1).repartition(4, "worker").select("worker"))["records"])
        placed.unpersist(), local.unpersist()
    assert sizes[0] == sizes[1] <= 8


def test_too_small_k_harms_and_the_signed_test_does_worse(spark, tiny):
    """Loose guards on a small table, not evidence: k = 4 against k = 65, and the signed comparison at k = 65."""
    problem = Problem(runs.small_blocks(spark, tiny), 64)
    spec = replace(SMALL, steps=120, sketch=SketchSpec(5, 128, 7))
    loss = lambda **o: np.mean(simulate(problem, replace(spec, **o))["losses"][-10:])
    assert loss(k=4) > loss(k=65) and loss(k=65, literal_signed=True) > loss(k=65)
    assert abs(loss(k=65) - loss(method="dense")) < 0.5


def test_sum_and_mean_differ_by_the_rate(small):
    a = train(small, replace(SMALL, steps=2))
    b = train(small, replace(SMALL, steps=2, combine="sum", rate=SMALL.rate / SMALL.workers))
    assert np.allclose(a.weights, b.weights)


def test_only_the_support_moves_without_residual(small):
    got = train(small, replace(SMALL, steps=1, residual="none", k=7))
    assert 0 < np.count_nonzero(got.weights) <= 7 and got.trace[0]["support"] == 7


def test_dense_training_learns_and_repeats(small):
    spec = replace(SMALL, method="dense", steps=15, evaluate_every=15)
    a, b = train(small, spec), train(small, spec)
    assert a.trace[-1]["loss"] < 0.8 * a.trace[0]["loss"] and np.array_equal(a.weights, b.weights)


def test_noise_labels_stay_at_chance(spark, tiny):
    noise = embedding_blocks(spark, tiny, 4, planted=False)
    got = train(noise, replace(SMALL, method="dense", steps=10, evaluate_every=10))
    assert got.trace[-1]["acc"] < 0.3


def test_large_problem_learns(spark, tiny):
    blocks = runs.large_blocks(spark, tiny, 3)
    got = train(blocks, replace(runs.LARGE, workers=3, steps=8, evaluate_every=8))
    assert got.trace[-1]["acc"] > 0.8
    assert evaluate(blocks, runs.LARGE.model, got.weights, held_out=False)[0] > 0.8


def test_warm_up_schedule(spark):
    rows = {r.epoch: r for r in warmup_schedule(spark, 7, 1000, 50, 200).collect()}
    assert [rows[e].k for e in range(7)] == [250, 73, 15, 4, 50, 50, 50]
    assert [rows[e].rate_permille for e in range(7)] == [100, 30, 10, 10, 200, 200, 200]
    assert all(schedule_at(e, 1000, 50, 0.2, True) == (rows[e].k, rows[e].rate_permille / 1000) for e in range(7))


@pytest.mark.parametrize("bad", [dict(method="ring"), dict(k=0), dict(residual="all"), dict(combine="max")])
def test_spec_rejects(bad):
    with pytest.raises(ValueError):
        TrainSpec(model=Softmax(2, 2), **bad)


def test_single_worker(spark, tiny):
    blocks = runs.small_blocks(spark, tiny, 1)
    got = train(blocks, replace(SMALL, workers=1, steps=2))
    assert len(got.trace) == 2 and sum(x[5] for x in got.ledger) == 0


def test_wide_blocks_are_scored_without_a_dense_matrix():
    """4,096 examples of 2^18 features would be 8 GB as a dense matrix."""
    import tracemalloc

    from treesketch.learning.blocks import Block

    rng = np.random.default_rng(3)
    n, features, each = 4096, 1 << 18, 20
    index = np.concatenate([rng.choice(features, each, replace=False) for _ in range(n)])
    parts = {"keys": np.arange(n), "labels": rng.integers(0, 4, n), "index": index, "value": rng.random(n * each), "starts": np.arange(0, n * each + 1, each)}
    block = Block({"n": n} | {c: v.tobytes() for c, v in parts.items()})
    model = Softmax(features, 4)
    w = rng.standard_normal(model.size)
    tracemalloc.start()
    scores, (grad, loss) = model.scores(w, block.rows(features)), model.gradient(w, block.rows(features), block.labels)
    assert tracemalloc.get_traced_memory()[1] < 200e6
    tracemalloc.stop()
    few = Block(block.some(np.arange(5)))
    assert np.allclose(model.scores(w, few.dense(np.arange(5), features)), scores[:5])
    dense, sparse = model.gradient(w, few.dense(np.arange(5), features), few.labels), model.gradient(w, few.rows(features), few.labels)
    assert np.allclose(dense[0], sparse[0]) and np.isclose(dense[1], sparse[1]) and len(grad) == model.size and loss > 0


def test_examples_are_read_twice_whatever_the_steps(spark, tiny):
    """All steps' mini-batches come from two passes over the blocks; each is the one that its step alone takes."""
    from treesketch.learning import trainer
    from treesketch.learning.blocks import Block, language_blocks

    read = spark.sparkContext.accumulator(0)

    def seen(batches):
        for batch in batches:
            read.add(batch.num_rows)
            yield batch

    blocks = runs.small_blocks(spark, tiny).persist()
    n = blocks.where("not held_out").count()
    counted = blocks.where("not held_out").mapInArrow(seen, blocks.schema)
    chosen = trainer.mini_batches(counted, 4, 16, 1, 12)
    got = {(r["step"], r["worker"]): r for r in chosen.collect()}
    assert read.value == 2 * n and set(got) == {(s, w) for s in range(1, 13) for w in range(4)}
    for step in (1, 7, 12):
        rows = trainer._minibatch(trainer.place(blocks, 4).coalesce(1), 16, 1, step).collect()
        assert all(sorted(Block(r.asDict()).keys) == Block(got[step, r["worker"]].asDict()).keys.tolist() for r in rows) and len(rows) == 4
    chosen.unpersist()
    whole, by_worker = language_blocks(spark, tiny, 0), language_blocks(spark, tiny, 3)
    a, b = ({(r["step"], r["worker"]): r["keys"] for r in trainer.mini_batches(x, 3, 8, 1, 2).collect()} for x in (whole, by_worker))
    assert a == b and len(a) == 6


def test_alone_runs_share_mini_batches_and_give_the_same(spark, tiny, monkeypatch):
    specs = runs.methods(replace(SMALL, steps=3, evaluate_every=3), ("tree_topk", "tree_sketch"))
    blocks = runs.small_blocks(spark, tiny).persist()
    calls, make = [], runs.mini_batches
    monkeypatch.setattr(runs, "mini_batches", lambda *a: calls.append(a) or make(*a))
    a, b = (runs.report(spark, blocks, specs, alone=alone).select("run", "loss", "acc", "values_sent").collect() for alone in (True, False))
    assert len(calls) == 1 and blocks.is_cached and [r.run for r in a] == [r.run for r in b]
    assert all(np.isclose(x.loss, y.loss) and x.acc == y.acc and x.values_sent == y.values_sent for x, y in zip(a, b))


def test_lengths_of_bags_are_not_computed_for_each_word(spark, tiny):
    from treesketch.learning.blocks import Block
    from treesketch.plans.rewrites import physical_plan

    blocks = runs.large_blocks(spark, tiny)
    assert "aggregate(" not in physical_plan(blocks)
    for row in blocks.collect():
        block = Block(row.asDict())
        assert np.allclose(np.add.reduceat(block.value**2, block.starts[:-1]), 1)
