from treesketch.functions import sqlapi
from treesketch.functions.hashing import SketchSpec
from treesketch.operators import sketch as sk
from treesketch.sources import tables

SPEC = SketchSpec(3, 512, 3)


def test_sql_functions(spark, tiny):
    sqlapi.register(spark, SPEC)
    v = tables.part_vector(spark, tiny)
    v.createOrReplaceTempView("v")
    got = spark.sql("SELECT coord, sketch_bucket_1(coord) AS b, sketch_sign_2(coord) AS s FROM v").collect()
    assert all(r.b == SPEC.np_buckets([r.coord])[1][0] and r.s == SPEC.np_signs([r.coord])[2][0] for r in got)
    cells = spark.sql("SELECT sketch_agg(coord, val) AS c FROM v").first()["c"]
    want = {(r.hrow, r.bucket): r.val for r in sk.merge_flat(sk.build(v, SPEC)).collect()}
    assert {(i // 512, i % 512): x for i, x in enumerate(cells) if x} == want
    assert len(spark.sql("SELECT * FROM tree_plan(7)").collect()) == 6 + 1
    top = spark.sql("SELECT * FROM sketch_top_k(TABLE(SELECT coord, val FROM v), 5)").collect()
    assert len(top) == 5


def test_generated_sql_equals_the_plan(spark, tiny):
    tables.part_vector(spark, tiny).createOrReplaceTempView("v2")
    assert sorted(map(tuple, spark.sql(sk.build_sql("v2", SPEC)).collect())) == sorted(map(tuple, sk.build(tables.part_vector(spark, tiny), SPEC).collect()))
