"""Tables written between jobs, in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def scratch_root(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` where it is set, else the warehouse; a local master without the setting gets a temporary folder."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root and spark.sparkContext.master.startswith("local["):
        root = tempfile.mkdtemp(prefix="treesketch-")
        spark.conf.set("spark.checkpoint.dir", root)
    return (root or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_treesketch").rstrip("/")


def scratch_path(spark: SparkSession, name: str) -> str:
    return f"{scratch_root(spark)}/{name}-{uuid.uuid4().hex}"


def keep(df: DataFrame, name: str) -> tuple[DataFrame, str]:
    """``df`` written as Parquet and read back, and its path. A lost executor costs no more than the tasks it ran."""
    path = scratch_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path), path


def drop(spark: SparkSession, path: str) -> bool:
    """Delete a written table, through Spark's own file system layer."""
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
