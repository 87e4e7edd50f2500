import numpy as np
import pytest

from treesketch.functions.hashing import PRIME, SketchSpec, fold_domain, np_fill_order, size_for
from treesketch.operators import sketch as sk
from treesketch.plans import rewrites
from treesketch.sources import sinks, synthetic, tables
from treesketch.sources.literals import literal_rows

SPEC = SketchSpec(5, 64, 3)


def vector(spark, pairs, kind="long"):
    return literal_rows(spark, [(w, c, v) for w, c, v in pairs], f"worker int, coord long, val {kind}")


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_coefficients_stay_in_range():
    for seed in range(50):
        for row in range(7):
            assert all(1 <= c < PRIME for c in SketchSpec(7, 10, seed).coefficients(row))


@pytest.mark.parametrize("bad", [dict(rows=4), dict(rows=0), dict(width=0)])
def test_spec_rejects(bad):
    with pytest.raises(ValueError):
        SketchSpec(**bad)


def test_spec_survives_json():
    assert SketchSpec.from_json(SPEC.to_json()) == SPEC


def test_sizes_grow_as_stated():
    assert size_for(10**6, 0.1).width == 100 and size_for(10**6, 0.1, form="inverse_eps").width == 10
    assert size_for(10**6, 0.1, alpha=0.5).width == 400
    assert all(size_for(d, 0.1).rows % 2 == 1 for d in (1, 10, 1000, 10**9))
    with pytest.raises(ValueError):
        size_for(10, 0)


def test_numpy_twin(spark):
    coord = np.array([0, 1, 2, 77, 4095, PRIME - 1])
    cells = sk.build(vector(spark, [(0, int(c), 1) for c in coord]), SPEC)
    want = {}
    buckets, signs = SPEC.np_buckets(coord), SPEC.np_signs(coord)
    for r in range(SPEC.rows):
        for b, s in zip(buckets[r], signs[r]):
            want[r, int(b)] = want.get((r, int(b)), 0) + int(s)
    assert {(x.hrow, x.bucket): x.val for x in cells.collect()} == {k: v for k, v in want.items() if v}


def test_linear(spark):
    a = vector(spark, [(0, i, i * 3 - 7) for i in range(50)])
    b = vector(spark, [(0, i * 2, 5 - i) for i in range(50)])
    both = sk.build(a.unionByName(b), SPEC)
    assert rows(sk.add(sk.build(a, SPEC), sk.build(b, SPEC)).select("worker", "hrow", "bucket", "val")) == rows(both)
    assert rows(rewrites.sketch_below_union([a, b], SPEC).select("worker", "hrow", "bucket", "val")) == rows(both)
    assert sk.subtract(sk.build(a, SPEC), sk.build(a, SPEC)).count() == 0
    assert rows(sk.scale(sk.build(a, SPEC), -1)) == rows(sk.build(a.selectExpr("worker", "coord", "-val AS val"), SPEC))
    assert sk.build(a.where("false"), SPEC).count() == 0


@pytest.mark.parametrize("n", [1, 7, 64])
def test_partitions_do_not_matter(spark, tiny, n):
    v = tables.part_vector(spark, tiny)
    assert rows(sk.build(v.repartition(n), SPEC)) == rows(sk.build(v, SPEC))


def test_single_coordinate_is_exact(spark):
    merged = sk.merge_flat(sk.build(vector(spark, [(0, 9, -42)]), SPEC))
    est = {r.coord: r.est for r in sk.estimate_blocks(merged, SPEC, sk.dimension(spark, 10)).collect()}
    assert est[9] == -42
    assert sk.l2_squared(merged, SPEC).first()["l2sq"] == 42 * 42


def test_both_point_queries_agree(spark, tiny):
    merged = sk.merge_flat(sk.build(tables.price_vector(spark, tiny), SPEC))
    asked = sk.dimension(spark, 300)
    assert rows(sk.estimate(merged, SPEC, asked)) == rows(sk.estimate_blocks(merged, SPEC, asked))


def test_empty_sketch_reads_as_zero(spark):
    merged = sk.merge_flat(sk.build(vector(spark, [(0, 1, 1)]).where("false"), SPEC))
    assert {r.est for r in sk.estimate_blocks(merged, SPEC, sk.dimension(spark, 5)).collect()} == {0}
    assert sk.l2_squared(merged, SPEC).first()["l2sq"] == 0


def test_invalid_rows_are_left_out(spark):
    odd = literal_rows(spark, [(0, None, 1.0), (0, 1, None), (0, -1, 1.0), (0, 2, float("nan")), (0, 3, float("inf")), (0, 4, 2.0)], "worker int, coord long, val double")
    assert [r.coord for r in sk.valid(odd).collect()] == [4]


def test_error_stays_below_the_norm_share(spark):
    """|est - true| <= 3 |g| / sqrt(width) for nearly all coordinates, over several seeds."""
    rng = np.random.default_rng(0)
    g = rng.standard_normal(2000)
    bad = 0
    for seed in range(20):
        spec = SketchSpec(7, 256, seed)
        coord = np.arange(len(g))
        buckets, signs = spec.np_buckets(coord), spec.np_signs(coord)
        table = np.stack([np.bincount(buckets[r], signs[r] * g, spec.width) for r in range(spec.rows)])
        est = np.sort(signs * np.take_along_axis(table, buckets, 1), axis=0)[3]
        bad += (np.abs(est - g) > 3 * np.linalg.norm(g) / 16).sum()
        l2 = np.sort((table**2).sum(1))[3]
        assert 0.8 < l2 / (g @ g) < 1.2
    assert bad <= 0.001 * 20 * len(g)


def test_compressed_before_the_shuffle(spark, tiny):
    assert rewrites.has_partial_aggregate_below_exchange(sk.build(tables.part_vector(spark, tiny), SPEC))


def test_blocks_have_a_size_limit(spark):
    with pytest.raises(ValueError):
        sk.block(vector(spark, []).selectExpr("0 AS hrow", "0 AS bucket", "val"), SketchSpec(5, 1 << 20))


def test_stored_sketches_add_up(spark, tiny, tmp_path):
    cells = sk.build(tables.part_vector(spark, tiny), SPEC)
    sinks.write_sketch(cells, f"{tmp_path}/s", SPEC)
    again = sinks.read_sketch(spark, f"{tmp_path}/s", SPEC)
    assert rows(sk.merge_flat(again)) == rows(sk.merge_flat(cells))
    assert sinks.read_sketch(spark, f"{tmp_path}/s", SketchSpec(5, 65, 3)).count() == 0


def test_synthetic_source(spark):
    synthetic.register(spark)
    df = spark.read.format("synthetic_gradient").options(d=100, workers=3, seed=2).load()
    assert df.count() == 300 and rows(df) == rows(spark.read.format("synthetic_gradient").options(d=100, workers=3, seed=2).load())


def test_fill_order_is_a_shared_permutation():
    first = np_fill_order(np.arange(5000), 1, 1)
    assert len(np.unique(first)) == 5000 and not np.array_equal(first, np_fill_order(np.arange(5000), 1, 2))


def test_large_keys_fold(spark):
    got = spark.range(1 << 40, (1 << 40) + 100).select(fold_domain(sk.F.col("id")).alias("c")).collect()
    assert all(0 <= r.c < PRIME for r in got)


def test_sketching_shuffles_fewer_bytes_than_the_vector(spark, tiny):
    """A narrow sketch of a long vector: what is shuffled is bounded by the cells of a task, whatever the rows."""
    narrow = SketchSpec(3, 8, 1)
    sketched = rewrites.shuffle_metrics(sk.build(tables.part_vector(spark, tiny, 1, summed=False), narrow))
    dense = rewrites.shuffle_metrics(tables.part_vector(spark, tiny, 1))
    assert sketched["exchanges"] == dense["exchanges"] == 1
    assert 0 < sketched["records"] <= narrow.size * 8 and sketched["bytes"] < dense["bytes"]
