"""Rewrites that the builder makes, since Catalyst has no rule for them, and looks at what Spark made of a plan."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame

from treesketch.functions.hashing import SketchSpec
from treesketch.operators import sketch as sk


def sketch_below_union(parts: list[DataFrame], spec: SketchSpec, by: tuple[str, ...] = ("worker",)) -> DataFrame:
    """The sketch of a union as the sum of the parts' sketches: parts are never unioned row by row."""
    return sk.add(*[sk.build(p, spec, by) for p in parts]) if len(parts) > 1 else sk.build(parts[0], spec, by)


def physical_plan(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def count_nodes(df: DataFrame) -> dict[str, int]:
    """How often the plan has each kind of exchange, join, aggregate and Python node."""
    found: dict[str, int] = {}
    for name in re.findall(r"(?:BroadcastExchange|(?<!Broadcast)Exchange hashpartitioning|Exchange SinglePartition|\w*HashJoin|SortMergeJoin|BroadcastNestedLoopJoin|CartesianProduct|HashAggregate|SortAggregate|MapInArrow|TakeOrderedAndProject)", physical_plan(df)):
        found[name] = found.get(name, 0) + 1
    return found


def has_partial_aggregate_below_exchange(df: DataFrame) -> bool:
    """Whether vectors are compressed before they are shuffled."""
    return bool(re.search(r"Exchange hashpartitioning[^\n]*\n[^\n]*(?:HashAggregate|WholeStageCodegen)[^\n]*(?:partial_sum|HashAggregate)", physical_plan(df)))


def shuffle_metrics(df: DataFrame) -> dict[str, int]:
    """Run ``df``, a small result, and return what its plan really shuffled: exchanges, bytes written, rows."""
    df.collect()
    out = {"exchanges": 0, "bytes": 0, "records": 0}

    def metric(node, name: str) -> int:
        found = node.metrics().get(name)
        return int(found.get().value()) if found.isDefined() else 0

    def walk(node) -> None:
        kind = node.getClass().getSimpleName()
        if kind == "AdaptiveSparkPlanExec":
            return walk(node.executedPlan())
        if kind.endswith("QueryStageExec"):
            return walk(node.plan())
        if kind == "ShuffleExchangeExec":
            out["exchanges"] += 1
            out["bytes"] += metric(node, "shuffleBytesWritten")
            out["records"] += metric(node, "shuffleRecordsWritten")
        children = node.children()
        for i in range(children.size()):
            walk(children.apply(i))

    walk(df._jdf.queryExecution().executedPlan())
    return out
