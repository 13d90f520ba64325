"""Sources and sinks: the given tables, transaction files, any format Spark reads, and saved representations."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str) -> None:
    """A temporary view for each given table."""
    for name in TABLES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def read(spark: SparkSession, fmt: str, path: str, schema: str | None = None, **options) -> DataFrame:
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write(df: DataFrame, fmt: str, path: str, mode: str = "errorifexists", partition_by: tuple[str, ...] = (), **options) -> None:
    writer = df.write.format(fmt).mode(mode).options(**options)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def read_transactions(spark: SparkSession, path: str, separator: str = r"\s+") -> DataFrame:
    """(basket_id, items): one basket for each line, items separated by white space. Empty lines are empty baskets."""
    items = F.filter(F.split("value", separator), lambda x: x != "")
    return spark.read.text(path).select(F.monotonically_increasing_id().alias("basket_id"), items.alias("items"))


def write_transactions(baskets: DataFrame, path: str) -> None:
    """The inverse of :func:`read_transactions` (basket ids are not kept)."""
    baskets.select(F.array_join("items", " ").alias("value")).write.text(path)


def write_bucketed(df: DataFrame, name: str, key: str, buckets: int = 64, mode: str = "errorifexists") -> None:
    """A catalog table in buckets by ``key``: later joins and groups by that key read it without a shuffle."""
    df.write.mode(mode).bucketBy(buckets, key).sortBy(key).saveAsTable(name)
