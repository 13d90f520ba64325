"""Working tables of iterative plans, in the folder that all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_root(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; only where a local session has none is a temporary folder made."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        root = "file://" + tempfile.mkdtemp(prefix="supportbounds-")
        spark.conf.set("spark.checkpoint.dir", root)
    return root.rstrip("/")


def new_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_root(spark)}/work/{name}-{uuid.uuid4().hex}"


def keep(df: DataFrame, name: str = "table") -> DataFrame:
    """Writes ``df`` and reads it back: lineage is cut and a lost executor costs its running tasks only."""
    path = new_folder(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def small(df: DataFrame, limit_bytes: int = 64 << 20) -> DataFrame:
    """``df`` with a broadcast hint if the optimiser knows it to be small, else as it is.

    Meant for tables just written by :func:`keep`, whose size is that of their files.
    """
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return F.broadcast(df) if size <= limit_bytes else df


def dense_ids(df: DataFrame, order: list, name: str) -> DataFrame:
    """``df`` with column ``name``: 0, 1, 2, ... in the given order, without bringing the rows into one task.

    Rows are range-partitioned and numbered inside their partition; the partitions' sizes (one row each) give the offsets.
    """
    marked = keep(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__m", F.monotonically_increasing_id()), "ordered")
    marked = marked.withColumn("__p", F.shiftright("__m", 33)).withColumn("__i", F.col("__m").bitwiseAND(F.lit((1 << 33) - 1)))
    sizes = {r["__p"]: r["n"] for r in marked.groupBy("__p").agg(F.count("*").alias("n")).collect()}  # one row for each partition
    at, offsets = 0, []
    for p in sorted(sizes):
        offsets.append((p, at))
        at += sizes[p]
    first = df.sparkSession.createDataFrame(offsets, "__p long, __first long")
    return marked.join(F.broadcast(first), "__p").withColumn(name, F.col("__first") + F.col("__i")).drop("__p", "__i", "__m", "__first")
