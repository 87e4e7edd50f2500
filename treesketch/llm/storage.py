"""Tables written between jobs, in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def scratch_root(spark: SparkSession) -> str:
    """The session's shared folder: ``spark.checkpoint.dir`` where it is set.

    Without that setting a temporary folder is made, which only a local master
    can use; on a cluster the warehouse folder serves instead.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if spark.sparkContext.master.startswith("local["):
        root = tempfile.mkdtemp(prefix="treesketch-")
    else:
        root = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_treesketch"
    spark.conf.set("spark.checkpoint.dir", root)
    return root


_WRITTEN: list[str] = []


def scratch_path(spark: SparkSession, name: str) -> str:
    _WRITTEN.append(f"{scratch_root(spark)}/{name}-{uuid.uuid4().hex}")
    return _WRITTEN[-1]


def written() -> int:
    """How many tables this process has written and not released."""
    return len(_WRITTEN)


def release_scratch(spark: SparkSession, since: int = 0, *, keep: int = 0) -> int:
    """Delete the tables that this process has written after the first ``since``, but for the last ``keep``; results read from them must be used up. Returns their number."""
    paths = _WRITTEN[since : len(_WRITTEN) - keep]
    del _WRITTEN[since : len(_WRITTEN) - keep]
    return sum(drop_scratch(spark, path) for path in paths)


#: Rows of text in an Arrow batch, at most.
BATCH_ROWS = 2_000


def small_batches(spark: SparkSession) -> None:
    """Bound the session's Arrow batches: whole texts are long, and both sides of the pipe hold a batch."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= BATCH_ROWS:
        spark.conf.set(key, BATCH_ROWS)


#: Files that a written table has for each core of the cluster, at most.
FILES_PER_CORE = 2


def materialize(df: DataFrame, name: str, *, whole: bool = False) -> DataFrame:
    """Write ``df`` as Parquet to the shared folder and read it back.

    Cuts the lineage so that a lost executor costs no more than the tasks it
    ran; the files outlive executors. They stay until ``release_scratch``.
    Many small partitions are joined to some files for each core: creating a
    file costs more than writing a few rows. ``whole`` is for tables as large
    as the documents: their partitions stay as they are.
    """
    spark = df.sparkSession
    path = scratch_path(spark, name)
    if not whole:
        df = df.coalesce(FILES_PER_CORE * spark.sparkContext.defaultParallelism)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


class Columns:
    """A frame under names of its own, so that no given name can clash with an operator's.

    ``frame`` has the columns ``_0, _1, ...``; ``[name]`` is the one of exactly
    that name, else the first that differs in case only. ``others(taken)`` are
    the columns that pass through: all but those whose names differ from one
    in ``taken`` in case at most. ``named`` gives a result its names back.
    """

    def __init__(self, df: DataFrame):
        self.names = df.columns
        self.frame = df.toDF(*[f"_{i}" for i in range(len(self.names))])
        self.types = [f.dataType.simpleString() for f in self.frame.schema.fields]

    def place(self, name: str) -> int:
        exact = [i for i, n in enumerate(self.names) if n == name]
        near = [i for i, n in enumerate(self.names) if n.lower() == name.lower()]
        if not near:
            raise ValueError(f"there is no column {name}")
        return (exact or near)[0]

    def __getitem__(self, name: str) -> str:
        return f"_{self.place(name)}"

    def others(self, taken: tuple[str, ...] = ()) -> list[int]:
        low = {t.lower() for t in taken}
        return [i for i, n in enumerate(self.names) if n.lower() not in low]

    def named(self, result: DataFrame, places: list[int], added: tuple[str, ...]) -> DataFrame:
        return result.toDF(*[self.names[i] for i in places], *added)


def only(df: DataFrame, *names: str) -> DataFrame:
    """The named columns and no others, whatever names the others have; see ``Columns``."""
    given = Columns(df)
    return given.frame.select(*[F.col(given[n]).alias(n) for n in names])


#: Document ids (8 bytes each) that may be broadcast; more are joined by a shuffle.
BROADCAST_IDS = 2_000_000


def named_in(docs: DataFrame, ids: DataFrame, column: str, how: str = "left_semi", *, limit: int = BROADCAST_IDS) -> DataFrame:
    """Rows of ``docs`` whose ``column`` is (or with ``left_anti`` is not) in ``ids`` of one column; that is broadcast if it has ``limit`` rows at most."""
    name = ids.columns[0]
    if ids.count() <= limit:
        ids = F.broadcast(ids)
    return docs.join(ids, F.col(column).cast("long") == F.col(name), how)


def drop_scratch(spark: SparkSession, path: str) -> bool:
    """Delete one written table, through Spark's own file system layer."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
