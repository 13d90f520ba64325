"""Helpers that the corpus operators share: working tables in the shared folder and text clean-up."""

from __future__ import annotations

import itertools
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Words are runs of characters other than the six ASCII blanks.
ASCII_BLANKS = r"[\x20\x09-\x0D]+"


def shared_root(spark: SparkSession) -> str:
    """The folder that the driver and every executor see (``spark.checkpoint.dir``).

    Only where the session names none (unit tests on one machine) is a temporary folder made.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        root = "file://" + tempfile.mkdtemp(prefix="supportbounds-")
        spark.conf.set("spark.checkpoint.dir", root)
    return root.rstrip("/")


def new_folder(spark: SparkSession, name: str) -> str:
    """A fresh path below the shared folder; nothing exists there yet."""
    return f"{shared_root(spark)}/work/{name}-{uuid.uuid4().hex}"


def keep(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back.

    This cuts the lineage (a lost executor costs only its running tasks) and fixes
    values such as ``monotonically_increasing_id`` for every later reader.
    """
    path = new_folder(df.sparkSession, name)
    df.write.option("compression", "zstd").parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.kept_at = path
    return out


def remove_folder(spark: SparkSession, path: str) -> None:
    """Deletes a folder below the shared one, through the file system that holds it."""
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def discard(*tables: DataFrame) -> None:
    """Deletes tables made by :func:`keep` that nothing reads any more."""
    for table in tables:
        remove_folder(table.sparkSession, table.kept_at)


def text_of(df: DataFrame, column: str = "text") -> Column:
    """The text column with null read as empty."""
    return F.coalesce(df[column].cast("string"), F.lit(""))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def bytes_on_disk(df: DataFrame) -> int:
    """Size that the optimiser has for ``df``; of a table just read from files, the size of the files."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


#: So many keys at most are handed to every task as one list (2 MB or so); more of them are joined.
LOOKUP_KEYS = 50_000


class Lookup:
    """A set of keys (h1, h2) that expressions can test, without moving the rows that are tested.

    The keys become a few constant arrays: h1 tells the bucket, and h2 stands at the bucket's place in one of the arrays.
    """

    def __init__(self, keys: list[tuple[int, int]]):
        self.buckets = 1 << max(0, (len(keys) - 1).bit_length())
        held: list[list[int]] = [[] for _ in range(self.buckets)]
        for h1, h2 in keys:
            held[h1 % self.buckets].append(h2)
        rows = [",".join(str(own[i]) if i < len(own) else "0" for own in held) for i in range(max(map(len, held)))]
        # strings for the planner to fold, instead of a literal for each key
        self.places = [F.split(F.lit(row), ",").cast("array<bigint>") for row in rows]

    def holds(self, h1: Column, h2: Column) -> Column:
        bucket = F.pmod(h1, F.lit(self.buckets)).cast("int")
        found = [F.get(row, bucket) == h2 for row in self.places] or [F.lit(False)]
        while len(found) > 1:
            found = [a | b for a, b in itertools.zip_longest(found[::2], found[1::2], fillvalue=F.lit(False))]
        return found[0]

    def marked(self, df: DataFrame, values: str, key: Callable[[Column], tuple[Column, Column]], out: str) -> DataFrame:
        """Adds ``out``: for each place of the array ``values``, whether the key of what is there is one of the set.

        Keys are columns of their own, so that none is made more than once; conditions on ``out`` must not be pushed below it.
        """
        df = df.withColumns({"__lookup_h1": F.transform(values, lambda x: key(x)[0]), "__lookup_h2": F.transform(values, lambda x: key(x)[1])})
        return df.withColumn(out, F.transform("__lookup_h1", lambda h, i: self.holds(h, F.get("__lookup_h2", i)))).drop("__lookup_h1", "__lookup_h2")


def lookup(keys: DataFrame, most: int = LOOKUP_KEYS) -> Lookup | None:
    """The distinct keys (h1, h2) as a list to look things up in, or None if there are more than ``most``."""
    if keys.count() > most:
        return None
    return Lookup([(r.h1, r.h2) for r in keys.select("h1", "h2").collect()])


#: Places of a bitmap: 2^20 words of 64 bits, 16 MB of keys and words at most, whatever the input.
_BITMAP = 1 << 26


def with_hint(rows: DataFrame, keys: DataFrame, key: str, out: str) -> DataFrame:
    """Adds ``out``: false if the row's key is surely not among ``keys``; the bitmap that is broadcast has a fixed size."""
    slot = F.pmod(F.xxhash64(key), F.lit(_BITMAP))
    word, bit = F.shiftright(slot, 6), slot.bitwiseAND(F.lit(63)).cast("int")
    one = F.call_function("shiftleft", F.lit(1).cast("long"), bit)
    bitmap = keys.select(word.alias("__word"), one.alias("b")).groupBy("__word").agg(F.bit_or("b").alias("__bits"))
    named = rows.withColumn("__word", word).withColumn("__bit", bit)
    return named.join(F.broadcast(bitmap), "__word", "left").withColumn(out, F.coalesce(F.getbit("__bits", F.col("__bit")) == 1, F.lit(False))).drop("__word", "__bit", "__bits")
