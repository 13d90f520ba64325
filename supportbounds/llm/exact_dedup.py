"""Exact duplicates by a stream with disk-backed state.

A stream reads the table's files and aggregates by digest. Its state (RocksDB, checkpointed in the shared folder,
never expired) has one entry per digest ever seen: how many rows, the identifier of the row that stays and the
locator of that row's content (file and row number). Rows are aggregated in their own task before they
meet the state, so copies of one text, however many, are one update per task. Later runs over new files go on from the
same checkpoint.

The row that stays and the size of its group are what the state says. A digest that is hit more than once is checked
in full: rows whose digest may be a hit (told by a bitmap of fixed size) are grouped by digest AND text, which compares all
bytes; the group must be the one that the state has counted, with the content at the state's locator in it. Should two texts share a digest,
the state's entry is no class, and their rows are told apart by the text itself.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from supportbounds.llm.common import keep, new_folder, text_of, with_hint

ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
#: The store, and no space set aside for files that stay small (each partition of the state has its own).
_STORE = {"spark.sql.streaming.stateStore.providerClass": ROCKSDB, "spark.sql.streaming.stateStore.rocksdb.allowFAllocate": "false"}

def sha256(text: Column) -> Column:
    return F.unhex(F.sha2(text, 256))


def update_state(
    spark: SparkSession, path: str, checkpoint: str, changes: str, text: str = "text", key: str = "doc_id", digest: Callable[[Column], Column] = sha256, max_files: int | None = None
) -> None:
    """Takes the files below ``path`` that the checkpoint has not seen into the state; changed entries are added to ``changes``."""
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema)
    if max_files:
        reader = reader.option("maxFilesPerTrigger", max_files)
    # as a pattern, since the source takes a plain path for a folder and the table may be one file
    path = path.rstrip("/")
    rows = reader.parquet(f"{path[:-1]}[{path[-1]}]")
    place = F.struct(F.col(key).isNotNull().alias("known"), F.col(key).alias("id"), F.col("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("row"))
    entries = rows.select(digest(text_of(rows, text)).alias("digest"), place.alias("place")).groupBy("digest").agg(F.max("place").alias("place"), F.count("*").alias("n"))

    def add(batch: DataFrame, number: int) -> None:
        # written by batch number: a batch that is repeated after a failure replaces its own files
        batch.write.mode("overwrite").option("compression", "zstd").parquet(f"{changes}/batch={number}")

    before = {k: spark.conf.get(k, None) for k in _STORE}
    for k, v in _STORE.items():
        spark.conf.set(k, v)
    try:
        query = entries.writeStream.outputMode("update").foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
        query.awaitTermination()
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def state(spark: SparkSession, changes: str, kind: str = "long") -> DataFrame:
    """digest, place, n: the newest value of every entry (counts and places only grow)."""
    fields = f"digest binary, place struct<known:boolean,id:{kind},file:string,row:long>, n long, batch int"
    return spark.read.schema(fields).parquet(changes).groupBy("digest").agg(F.max("place").alias("place"), F.max("n").alias("n"))


def find(spark: SparkSession, path: str, text: str = "text", key: str = "doc_id", digest: Callable[[Column], Column] = sha256, max_files: int | None = None, folder: str | None = None) -> DataFrame:
    """One row per row of the Parquet table at ``path``: key, keep_id, group_size, kept, text_sha256.

    Of equal texts the row with the largest key stays. A null text equals an empty one. Null keys are below all others; of rows
    that share key and text (or have no key) the last one in (file, row) order stays, so each group keeps one row. An
    empty table gives an empty result; texts of any length are compared whole; further columns do not matter. ``folder``: where state and
    changes live, for runs that go on later with files added to the table.
    """
    folder = folder or new_folder(spark, "exact-dedup")
    update_state(spark, path, f"{folder}/state", f"{folder}/changes", text, key, digest, max_files)
    docs = spark.read.parquet(path)
    kind = docs.schema[key].dataType.simpleString()
    if docs.limit(1).count() == 0:
        entries = spark.createDataFrame([], f"digest binary, place struct<known:boolean,id:{kind},file:string,row:long>, n long")
    else:
        entries = keep(state(spark, f"{folder}/changes", kind), "dedup-state")
    hits = entries.where("n > 1")
    place = F.struct(F.col(key).isNotNull().alias("known"), F.col(key).alias("id"), F.col("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("row"))
    rows = docs.select(F.col(key).alias("id"), text_of(docs, text).alias("text"), place.alias("place"))
    rows = rows.withColumn("digest", digest(F.col("text")))
    groups = with_hint(rows, hits, "digest", "__hit").where("__hit").groupBy("digest", "text").agg(F.count("*").alias("n"), F.max("place").alias("place"))
    checked = keep(groups.select("digest", F.sha2("text", 256).alias("text_sha256"), "n", "place"), "checked-groups")
    told = checked.groupBy("digest").agg(F.count("*").alias("texts"), F.max("place").alias("found_place"), F.sum("n").alias("found_n"))
    compared = keep(hits.join(told, "digest", "left"), "compared-hits")
    off, clashes = compared.agg(
        F.count_if(~F.coalesce((F.col("found_n") == F.col("n")) & (F.col("found_place") == F.col("place")), F.lit(False))), F.count_if(F.col("texts") > 1)
    ).first()
    if off:
        raise ValueError(f"{off} entries of the state do not agree with the table: files that it has seen are gone or changed")
    light = rows.select("id", "digest", F.struct("place.file", "place.row").alias("at"), F.sha2("text", 256).alias("text_sha256"))
    many = compared.where("texts = 1").select("digest", "n", "place")
    on = ["digest"]
    if clashes:  # a short digest: classes of such entries are told apart by the longer one, whose groups were compared in full
        on = ["digest", "text_sha256"]
        many = checked.where("n > 1").select("digest", "text_sha256", "n", "place")
    out = light.join(many, on, "left")
    stays = F.col("place").isNull() | (F.col("at") == F.struct(F.col("place.file").alias("file"), F.col("place.row").alias("row")))
    return out.select(
        F.col("id").alias(key), F.coalesce("place.id", "id").alias("keep_id"), F.coalesce("n", F.lit(1)).cast("long").alias("group_size"), stays.alias("kept"), "text_sha256"
    )


ORACLE = """
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = max(doc_id) OVER w AS kept, sha256(coalesce(text, '')) AS text_sha256
FROM documents WINDOW w AS (PARTITION BY coalesce(text, ''))
"""
