import numpy as np
import pytest
from pyspark.sql import functions as F

from treesketch.functions import cost
from treesketch.functions.hashing import SketchSpec
from treesketch.learning.trainer import np_recover, np_sketch, np_top
from treesketch.operators import compressors, measures, recovery, topology
from treesketch.operators import sketch as sk
from treesketch.plans import rewrites
from treesketch.plans.steps import apply_update, method_step, sketch_step
from treesketch.sources import tables
from treesketch.sources.literals import literal_rows

SPEC = SketchSpec(5, 128, 5)


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.mark.parametrize("p", [1, 2, 3, 5, 6, 7, 8, 13, 17])
def test_tree_plan(spark, p):
    edges = topology.tree_edges(spark, p).collect()
    merges = [e for e in edges if e.kind == "merge"]
    assert len(merges) == p - 1 and {e.src for e in merges} == set(range(1, p))
    assert max((e.round for e in edges), default=0) == topology.rounds(p)
    held = {w: {w} for w in range(p)}
    for e in sorted(merges, key=lambda e: e.round):
        held[e.dst] |= held[e.src]
    assert held[0] == set(range(p))
    assert all(sum(e.kind == "bye" and e.round == r for e in edges) <= 1 for r in range(1, 6))
    down = topology.tree_edges(spark, p, "down").collect()
    known = {0}
    for e in sorted(down, key=lambda e: e.round):
        assert e.src in known
        known.add(e.dst)
    assert known == set(range(p))


@pytest.mark.parametrize("p", [1, 3, 8, 11])
def test_tree_equals_flat(spark, tiny, p):
    cells = sk.build(tables.price_vector(spark, tiny, p), SPEC)
    assert rows(topology.tree_merge(cells, p)) == rows(sk.merge_flat(cells)) == rows(topology.star_merge(cells))


def test_tree_merge_shuffles_once(spark, tiny):
    cells = sk.build(tables.part_vector(spark, tiny, 8), SPEC).select("worker", "hrow", "bucket", "val")
    before = rewrites.physical_plan(cells).count("Exchange hashpartitioning")
    assert rewrites.physical_plan(topology.tree_merge(cells, 8)).count("Exchange hashpartitioning") <= before + 1


def test_empty_worker_and_more_workers_than_rows(spark):
    v = literal_rows(spark, [(2, 5, 10)], "worker int, coord long, val long")
    assert rows(sketch_step(v, SPEC, d=20, k=1, workers=7)) == [(5, 10, True, 10)]


def test_literal_stride_loses_workers(spark):
    got = {r.workers: r.covered for r in topology.literal_stride_coverage(spark, [1, 2, 4, 5, 8, 16]).collect()}
    assert got == {1: 1, 2: 2, 4: 4, 5: 4, 8: 4, 16: 8}


def test_support_has_min_k_d_and_exact_sums(spark, tiny):
    v = tables.part_vector(spark, tiny)
    truth = {r.coord: r.val for r in compressors.dense_sum(v).collect()}
    for k, d in ((10, 201), (500, 201)):
        got = sketch_step(v, SPEC, d=d, k=k, workers=4).collect()
        assert len(got) == min(k, d) and all(r.exact == truth.get(r.coord, 0) for r in got)


def test_k_of_d_is_the_dense_step(spark, tiny):
    v = tables.part_vector(spark, tiny)
    dense = rows(method_step(v, "dense", SPEC, d=201, k=1, workers=4))
    assert [x for x in rows(method_step(v, "tree_sketch", SPEC, d=201, k=201, workers=4)) if x[1]] == dense
    assert rows(method_step(v, "tree_topk", SPEC, d=201, k=201, workers=4)) == dense == rows(method_step(v, "star_topk", SPEC, d=201, k=201, workers=4))


def test_numpy_twin_of_a_step(spark, tiny):
    v = tables.token_vector(spark, tiny, 4, 512)
    dense = np.zeros(512)
    for r in compressors.dense_sum(v).collect():
        dense[r.coord] = r.val
    coord = np.arange(512)
    cells = np_sketch(dense, SPEC, SPEC.np_buckets(coord), SPEC.np_signs(coord))
    for how in ("heavy_random", "top_estimate", "heavy_only"):
        support, est, _ = np_recover(cells, SPEC, 512, 40, how, 1, 1)
        got = sorted((r.coord, r.est) for r in sketch_step(v, SPEC, d=512, k=40, workers=4, recover=how).collect())
        assert got == list(zip(support.tolist(), est.tolist()))


def test_more_heavies_than_k_and_none(spark):
    wide = SketchSpec(5, 4096, 1)
    est = literal_rows(spark, [(0, -9), (1, 8), (2, 8), (3, 1)], "coord long, est long")
    low = literal_rows(spark, [(20,)], "l2sq long")
    split = recovery.split_heavy(est, low.selectExpr("CAST(l2sq AS DECIMAL(38,0)) AS l2sq"), 2)
    assert [(r.coord, r.heavy) for r in recovery.heavy_random(split, 2, 1, 1).collect()] == [(0, True), (1, True)]
    assert sorted(r.coord for r in recovery.heavy_only(split, 2).collect()) == [0, 1]
    flat = literal_rows(spark, [(0, c, 1) for c in range(400)], "worker int, coord long, val long")
    assert not any(r.heavy for r in sketch_step(flat, wide, d=400, k=3, workers=1).collect())


def test_signed_test_misses_negative_coordinates(spark):
    v = literal_rows(spark, [(0, 3, -1000), (0, 4, 900)], "worker int, coord long, val long")
    heavy = lambda signed: {r.coord for r in sketch_step(v, SketchSpec(5, 1024, 1), d=30, k=3, workers=1, recover="heavy_only", literal_signed=signed).collect()}
    assert heavy(False) == {3, 4} and 3 not in heavy(True)


def test_cancelling_workers(spark):
    v = literal_rows(spark, [(0, 1, 5), (1, 1, -5), (1, 2, 3)], "worker int, coord long, val long")
    assert rows(compressors.dense_sum(v)) == [(2, 3)]
    assert rows(compressors.tree_topk(v, 1, 2)) == []


def test_ties_go_to_the_smaller_coordinate(spark):
    v = literal_rows(spark, [(0, c, (-1) ** c) for c in range(6)], "worker int, coord long, val long")
    assert rows(compressors.local_topk(v, 2)) == [(0, 0, 1), (0, 1, -1)]
    assert np_top(np.array([1.0, -1.0, 1.0]), 2).tolist() == [0, 1]


def test_threshold_top_equals_sorted_top(spark, tiny, monkeypatch):
    v = compressors.dense_sum(tables.part_vector(spark, tiny))
    want = rows(compressors.exact_topk(tables.part_vector(spark, tiny), 77))
    monkeypatch.setattr(recovery, "THRESHOLD_K", 1)
    assert rows(recovery._top(v, [F.abs("val").desc(), F.col("coord")], 77, F.abs("val"))) == want


def test_update_touches_the_support_only(spark):
    w = literal_rows(spark, [(0, 1.0), (1, 2.0)], "coord long, w double")
    g = literal_rows(spark, [(1, 4.0), (7, 8.0)], "coord long, exact double")
    assert rows(apply_update(w, g, 0.5, workers=4)) == [(0, 1.0), (1, 1.5), (7, -1.0)]
    assert rows(apply_update(w, g, 0.5, combine="sum")) == [(0, 1.0), (1, 0.0), (7, -4.0)]


@pytest.mark.parametrize("p", list(range(1, 18)))
def test_ledger_closed_forms(p):
    size, d, k, r = 640, 1000, 10, topology.rounds(p)
    total = lambda m, phase, direction: tuple(map(sum, zip(*[(x[4], x[5]) for x in topology.ledger_lines(m, p, d=d, k=k, size=size) if x[1:3] == (phase, direction)]))) or (0, 0)
    for direction in ("up", "down"):
        assert total("tree_sketch", "sketch", direction) == (p - 1, (p - 1) * size)
        assert total("tree_sketch", "exact", direction) == (p - 1, (p - 1) * k)
        assert total("dense", "dense", direction) == (p - 1, (p - 1) * d)
        assert total("star_sketch", "sketch", direction) == (p, p * size)
    assert max((x[3] for x in topology.ledger_lines("tree_topk", p, d=d, k=k, size=size)), default=0) == r


def test_cost_relations(spark):
    g = cost.grid(spark, workers=[2, 4, 64], dims=[10**6], densities_ppm=[4_000], alphas=[10**4])
    t = {(r.workers, r.method): r for r in g.collect()}
    for p in (2, 4, 64):
        assert t[p, "tree_sketch"].t <= t[p, "star_sketch"].t and t[p, "tree_sketch"].t_paper < t[p, "tree_sketch"].t
        assert t[p, "star_sketch"].t * topology.rounds(p) == t[p, "tree_sketch"].t * p


def test_quantized_values_are_near(spark, tiny):
    v = tables.token_vector(spark, tiny, 2, 256)
    q = compressors.quantize(v, 12).join(v.withColumnRenamed("val", "true"), ["worker", "coord"])
    worst = q.join(v.groupBy("worker").agg(F.max("val").alias("m")), "worker").select(F.max(F.abs(F.col("val") - F.col("true")) / F.col("m")).alias("e")).first()["e"]
    assert worst <= 0.5 / 2047 + 1e-9


def test_builtin_top_runs(spark, tiny):
    words = tables.read_table(spark, tiny, "documents").select("source")
    assert compressors.builtin_top(words, "source", 5).count() == 5


def test_measures(spark):
    curves = literal_rows(spark, [("a", e, v) for e, v in enumerate([0.1, 0.5, 0.79, 0.6, 0.8, 0.81, 0.8])], "method string, epoch int, acc double")
    assert measures.epochs_to_converge(curves, 0.05).first()["epoch"] == 4
    trace = literal_rows(spark, [("m", "x", 100, 2.0, 1.0, 0.5, 0.5), ("m", "x", 100, 2.0, 1.0, 0.5, 0.5)], "model string, method string, examples int, seconds double, t_compute double, t_compress double, t_comm double")
    assert measures.throughput(trace).first()["examples_per_s"] == 50
    assert measures.comm_share(trace).first()["comm_share"] == 0.25
    rates = literal_rows(spark, [("x", 1, 10.0), ("x", 4, 20.0)], "method string, workers int, examples_per_s double")
    assert {r.workers: r.efficiency for r in measures.scaling_efficiency(rates).collect()} == {1: 1.0, 4: 0.5}


def test_large_k_finds_a_threshold_first(spark):
    """For k = 5,000 the same rows as by plain ordering, without a driver merge of k rows of each task."""
    import numpy as np

    from treesketch.functions.hashing import np_fill_order
    from treesketch.operators import compressors, recovery
    from treesketch.plans.rewrites import physical_plan

    n, k = 20_000, 5_000
    value = F.expr("CAST(CASE WHEN id % 7 = 0 THEN -1 ELSE 1 END * pmod(id * 7919, 1009) AS BIGINT)")
    coords = spark.range(2 * n).select((F.col("id") % 2).cast("int").alias("worker"), F.floor(F.col("id") / 2).alias("coord"), value.alias("val"))
    table: dict[int, dict[int, int]] = {0: {}, 1: {}}
    for r in coords.collect():
        table[r.worker][r.coord] = r.val
    best = lambda d, k: sorted((c for c in d if d[c]), key=lambda c: (-abs(d[c]), c))[:k]
    got = compressors.local_topk(coords, k)
    assert "TakeOrdered" not in physical_plan(got)
    assert sorted((r.worker, r.coord) for r in got.collect()) == sorted((w, c) for w in table for c in best(table[w], k))
    total = {c: table[0][c] + table[1][c] for c in table[0]}
    assert {r.coord for r in compressors.exact_topk(coords, k).collect()} == set(best(total, k))
    drawn = lambda cs: sorted(cs, key=lambda c: (int(np_fill_order(np.array([c]), 3, 4)[0]), c))
    some = compressors.random_k(coords, k, 3, 4)
    assert "TakeOrdered" not in physical_plan(some) and {r.coord for r in some.collect()} == set(drawn([c for c in total if total[c]])[:k])
    split = spark.range(n).select(F.col("id").alias("coord"), (F.col("id") % 1013 - 500).alias("est")).withColumn("heavy", F.abs("est") > 450)
    rows = {r.coord: r for r in split.collect()}
    heavy = [c for c in rows if rows[c].heavy]
    fill = drawn([c for c in rows if not rows[c].heavy])
    whole = recovery.heavy_random(split, k, 3, 4)
    assert "TakeOrdered" not in physical_plan(whole) and {r.coord for r in whole.collect()} == set(heavy) | set(fill[: k - len(heavy)])
    assert {r.coord for r in recovery.heavy_random(split, 1_500, 3, 4).collect()} == set(best({c: rows[c].est for c in heavy}, 1_500))


def test_a_million_cells_make_a_block_in_seconds(spark):
    import time


    spec = SketchSpec(5, 200_000, 7)
    cells = spark.range(spec.size).where("id % 3 <> 1").select(F.floor(F.col("id") / spec.width).cast("int").alias("hrow"), (F.col("id") % spec.width).cast("int").alias("bucket"), (F.col("id") + 1).alias("val"))
    began = time.perf_counter()
    got = sk.block(cells, spec).select(F.size("cells").alias("n"), F.aggregate("cells", F.lit(0).cast("long"), lambda s, x: s + x).alias("s"), F.get("cells", F.lit(999_999)).alias("last"), F.get("cells", F.lit(1)).alias("gap")).first()
    assert time.perf_counter() - began < 60
    assert got.n == spec.size and got.s == sum(i + 1 for i in range(spec.size) if i % 3 != 1) and got.last == 1_000_000 and got.gap == 0
    assert sk.block(cells.limit(0), SketchSpec(3, 4, 7)).first().cells == [0] * 12


def test_unfit_rows_are_counted_or_stop_the_job(spark):
    from pyspark.errors import PySparkException


    rows = [(0, 1, 1.0), (0, None, 1.0), (0, -1, 1.0), (0, 2**31 - 1, 1.0), (0, 3, None), (0, 4, float("nan")), (0, 5, float("-inf")), (0, None, None)]
    coords = spark.createDataFrame(rows, "worker int, coord long, val double")
    assert {r.reason: r.n for r in sk.rejected(coords).collect()} == {"no coordinate": 2, "coordinate out of range": 2, "no value": 1, "value not finite": 2}
    assert [r.coord for r in sk.valid(coords).collect()] == [1] and sk.checked(sk.valid(coords)).count() == 1
    with pytest.raises(PySparkException):
        sk.checked(coords).collect()
