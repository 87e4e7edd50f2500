"""The registered training queries run the whole experiments, and give the measures."""

import time
from contextlib import suppress
from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from treesketch.experiments import runs
from treesketch.learning.schedule import schedule_at


class Rows:
    schema = "x int"

    def __getattr__(self, name):
        return lambda *a, **k: self


def test_registered_runs_have_their_steps_and_grids(monkeypatch):
    seen = {}
    for name in ("small_blocks", "large_blocks", "modelled"):
        monkeypatch.setattr(runs, name, lambda *a: Rows())
    monkeypatch.setattr(runs, "language_blocks", lambda *a, **k: None)
    monkeypatch.setattr(runs, "once", lambda name, spark, sf, make: make())
    monkeypatch.setattr(runs, "convergence", lambda rows: rows)
    for name, query in runs.queries().items():
        specs = {}
        monkeypatch.setattr(runs, "report", lambda spark, blocks, s, specs=specs, **_: specs.update(s) or Rows())
        try:
            query(None, "")
        except Exception:  # measures of rows that are none
            pass
        seen[name] = specs
    for name in ("train_small", "k_sweep", "ablations", "equal_volume"):
        assert all(s.steps == 100 and s.model == runs.SMALL.model for s in seen[name].values())
    for name in ("train_large", "k_sweep_large"):
        assert all(s.steps == 40 for s in seen[name].values())
    assert set(seen["train_small"]) == set(seen["train_large"]) == set(runs.METHODS)
    assert {s.k for s in seen["k_sweep"].values()} == {4, 16, 65, 162}
    assert {s.k for s in seen["k_sweep_large"].values()} == {64, 256, 1024, 4096}
    assert {s.workers for s in seen["scaling"].values()} >= {1}
    assert seen["train_wide"]["tree_sketch"].model.features == 1 << 18 and seen["train_hidden"]["tree_sketch"].model == runs.SMALL_HIDDEN.model
    warm = seen["ablations"]["warm_up"]
    assert schedule_at((warm.steps - 1) // warm.steps_per_epoch, warm.model.size, warm.k, warm.rate, True)[0] == warm.k


@pytest.fixture(scope="module")
def short():
    return {"small": replace(runs.SMALL, steps=4, steps_per_epoch=2, evaluate_every=2), "large": replace(runs.LARGE, steps=3, evaluate_every=3)}


def test_measures_of_runs(spark, tiny, short, monkeypatch):
    trace = runs.report(spark, runs.small_blocks(spark, tiny), runs.methods(short["small"], runs.TIMED), every_step=True)
    curve = {(r.method, r.epoch): r for r in runs.convergence(trace).collect()}
    assert set(curve) == {(m, e) for m in runs.TIMED for e in (0, 1)} and all(r.settled in (0, 1) for r in curve.values())
    assert curve["tree_sketch", 1].values_sent == 2 * curve["tree_sketch", 0].values_sent
    monkeypatch.setattr(runs, "TIMED_STEPS", 2)
    rows = runs.timed(spark, tiny).persist()
    split = {(r.model, r.method): r for r in runs.time_split(rows).collect()}
    rates = {(r.model, r.method): r for r in runs.throughput(rows, {"small": 64, "large": 32}).collect()}
    assert set(split) == set(rates) == {(m, t) for m in ("small", "large") for t in runs.TIMED}
    assert all(0 < r.comm_share < 1 and 0 < r.modelled_share < 1 for r in split.values())
    for model in ("small", "large"):  # four workers: two rounds each way against four messages each way
        assert split[model, "star_sketch"].t_modelled == pytest.approx(2 * split[model, "tree_sketch"].t_modelled)
        over = rates[model, "star_sketch"]
        assert over.speedup == pytest.approx(rates[model, "tree_sketch"].examples_per_s / over.examples_per_s) and over.modelled_speedup > 0
    assert rates["small", "tree_sketch"].speedup is None
    found = {(r.method, r.workers): r for r in runs.scaling(spark, tiny, [1, 2], replace(short["large"], steps=2, evaluate_every=2), ("tree_sketch",)).collect()}
    assert found["tree_sketch", 1].efficiency == 1 and found["tree_sketch", 2].modelled_efficiency < 1


def test_scaling_times_each_method_alone(spark, tiny, short):
    """Methods that shared their jobs had one rate and one efficiency at a number of workers."""
    spec = replace(short["large"], steps=2, evaluate_every=2)
    found = runs.scaling(spark, tiny, [1, 2], spec).collect()
    assert {(r.method, r.workers) for r in found} == {(m, p) for m in runs.COMPARED for p in (1, 2)}
    for p in (1, 2):
        assert len({r.examples_per_s for r in found if r.workers == p}) == len({r.t_comm for r in found if r.workers == p}) == len(runs.COMPARED)
    assert len({r.efficiency for r in found if r.workers == 2}) == len(runs.COMPARED)


def test_a_timed_step_has_its_mini_batch_and_recovery(spark, tiny, short, monkeypatch):
    """Choosing the mini-batches counts in the examples a second; recovery and update count beside the modelled exchange."""
    make = runs.mini_batches
    monkeypatch.setattr(runs, "mini_batches", lambda *a: time.sleep(8) or make(*a))
    spec = replace(short["small"], steps=2, evaluate_every=2)
    rows = runs.report(spark, runs.small_blocks(spark, tiny), runs.methods(spec, ("tree_sketch",)), alone=True)
    (row,) = runs.modelled(rows, spec.model.size, spec.sketch.size).collect()
    assert row.t_sample > 4 and row.t_recover > 0 and row.examples_per_s < spec.workers * spec.batch / row.t_sample
    one = spark.createDataFrame([row]).withColumns({"t_recover": F.lit(3.0), "model": F.lit("small")})
    step = row.t_compute + row.t_compress + 3 + row.t_modelled
    assert runs.throughput(one, {"small": spec.batch}).first().modelled_per_s == pytest.approx(spec.workers * spec.batch / step)


def test_scaling_has_all_steps_of_the_large_run(monkeypatch):
    seen = []
    monkeypatch.setattr(runs, "large_blocks", lambda *a: Rows())
    monkeypatch.setattr(runs, "report", lambda spark, blocks, specs, **options: seen.append((specs, options)) or Rows())
    monkeypatch.setattr(runs, "modelled", lambda *a: Rows())
    with suppress(Exception):  # measures of rows that are none
        runs.queries()["scaling"](None, "")
    assert [{s.workers for s in specs.values()} for specs, _ in seen] == [{p} for p in runs.WORKERS]
    assert all(options == {"alone": True} and {s.steps for s in specs.values()} == {runs.LARGE_STEPS} for specs, options in seen)


def test_throughput_times_whole_runs_of_every_method(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(runs, "once", lambda name, spark, sf, make: make())
    for name in ("small_blocks", "large_blocks", "modelled"):
        monkeypatch.setattr(runs, name, lambda *a: Rows())
    monkeypatch.setattr(runs, "report", lambda spark, blocks, specs, **options: seen.append((specs, options)) or Rows())
    runs.queries()["throughput"](spark, "")
    assert [{s.steps for s in specs.values()} for specs, _ in seen] == [{runs.SMALL_STEPS}, {runs.LARGE_STEPS}]
    assert all({s.method for s in specs.values()} == set(runs.METHODS) and options == {"alone": True} for specs, options in seen)
