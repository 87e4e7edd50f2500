"""The sketch for SQL users: table functions, an aggregate, and bucket and sign as SQL functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from treesketch.functions.hashing import SketchSpec


def _tree_plan():
    @udtf(returnType="round int, src long, dst long, kind string")
    class TreePlan:
        def eval(self, workers: int):
            count, stride, step = workers, 1, 1
            while count > 1:
                for j in range(1, count, 2):
                    yield step, j * stride, (j - 1) * stride, "merge"
                if count % 2:
                    yield step, (count - 1) * stride, (count - 1) * stride, "bye"
                count, stride, step = (count + 1) // 2, 2 * stride, step + 1

    return TreePlan


def _top_k(spec: SketchSpec):
    @udtf(returnType="coord long, est double")
    class SketchTopK:
        """Sketches its rows and returns the k seen coordinates of largest estimate."""

        def __init__(self):
            self._sums: dict[int, float] = {}
            self._k = 0

        def eval(self, row: Row, k: int):
            self._k = k
            self._sums[row["coord"]] = self._sums.get(row["coord"], 0.0) + float(row["val"])

        def terminate(self) -> Iterator:
            if not self._sums:
                return
            coord, val = np.array(list(self._sums)), np.array(list(self._sums.values()))
            buckets, signs = spec.np_buckets(coord), spec.np_signs(coord)
            table = np.stack([np.bincount(buckets[r], signs[r] * val, spec.width) for r in range(spec.rows)])
            est = np.sort(signs * np.take_along_axis(table, buckets, 1), axis=0)[spec.rows // 2]
            for i in np.lexsort((coord, -np.abs(est)))[: self._k]:
                yield int(coord[i]), float(est[i])

    return SketchTopK


def sketch_agg(spec: SketchSpec):
    """A grouped aggregate (coord, val) -> all cells, row after row. For groups that fit a task; ``operators.sketch.build`` has no such limit."""

    @pandas_udf("array<double>")
    def aggregate(coord: pd.Series, val: pd.Series) -> list:
        c, v = coord.to_numpy(), val.to_numpy(np.float64)
        buckets, signs = spec.np_buckets(c), spec.np_signs(c)
        return np.concatenate([np.bincount(buckets[r], signs[r] * v, spec.width) for r in range(spec.rows)]).tolist()

    return aggregate


def register(spark: SparkSession, spec: SketchSpec) -> None:
    """``tree_plan(P)``, ``sketch_top_k(TABLE(...), k)``, ``sketch_agg(coord, val)``, and ``sketch_bucket_r(coord)``, ``sketch_sign_r(coord)`` for each row r, which are plain SQL expressions."""
    spark.udtf.register("tree_plan", _tree_plan())
    spark.udtf.register("sketch_top_k", _top_k(spec))
    spark.udf.register("sketch_agg", sketch_agg(spec))
    for r in range(spec.rows):
        a, b, c3, c2, c1, c0 = spec.coefficients(r)
        names = {"a": a, "b": b, "c3": c3, "c2": c2, "c1": c1, "c0": c0}
        for kind, text, result in (("bucket", spec.sql_bucket("i"), "INT"), ("sign", spec.sql_sign("i"), "BIGINT")):
            for name, value in names.items():
                text = _replace_word(text, name, f"{value}L")
            spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sketch_{kind}_{r}(i BIGINT) RETURNS {result} RETURN {text}")


def _replace_word(text: str, name: str, value: str) -> str:
    import re

    return re.sub(rf"\b{name}\b", value, text)


def sketch_expression(kind: str, coord: str, spec: SketchSpec, row: int):
    """``bucket`` or ``sign`` of a column as an expression of built-in functions."""
    column = F.col(coord).cast("long")
    return spec.bucket(column, row) if kind == "bucket" else spec.sign(column, row)
