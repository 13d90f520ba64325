"""Streams: windowed baskets, supports of fixed itemsets, late rows, state across batches, joins and duplicates.

Only a fixed set of itemsets can be counted exactly on a stream: a set that becomes a candidate later would need
baskets that are gone. Every query here runs through the rows that are there (trigger ``availableNow``) and ends with the same result as the
batch query over them; with another trigger it goes on.
"""

from __future__ import annotations

import threading
import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.listener import StreamingQueryListener
from pyspark.sql.streaming.state import GroupState
from pyspark.sql.types import IntegerType, StructField, StructType

from supportbounds.operators import rules
from supportbounds.operators.itemsets import contains_all
from supportbounds.plans.workspace import new_folder


def events(spark: SparkSession, sf_dir: str, max_files: int = 1000) -> DataFrame:
    """The events table as a stream (its path written as a pattern: it may be one file). ``ts`` is read as UTC."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(f"{path[:-1]}[{path[-1]}]")
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def run_to_end(stream: DataFrame, mode: str = "append", keys: list[str] | None = None) -> DataFrame:
    """Runs a stream over what is there and returns its result as a table.

    Batches are written by number into the shared folder, so a repeated batch replaces its files. With
    ``keys`` the newest row of each key is taken (update mode).
    """
    spark = stream.sparkSession
    folder = new_folder(spark, "stream")
    schema = stream.schema

    def sink(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out/batch={number}")

    stream.writeStream.outputMode(mode).foreachBatch(sink).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    fields = schema.fields
    read_schema = StructType([*fields, StructField("batch", IntegerType())])
    out = spark.read.schema(read_schema).parquet(f"{folder}/out")
    if keys:
        newest = F.max(F.struct("batch", *[F.col(f.name) for f in fields if f.name not in keys])).alias("v")
        out = out.groupBy(*keys).agg(newest).select(*keys, *[F.col(f"v.{f.name}").alias(f.name) for f in fields if f.name not in keys])
        return out.select(*[f.name for f in fields])
    return out.drop("batch")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events per kind and day."""
    counted = events(spark, sf_dir).withWatermark("ts", "40000 days").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("cnt"))
    flat = counted.select(F.unix_seconds("window.start").alias("window_start"), "event_type", "cnt")
    return run_to_end(flat, "update", ["window_start", "event_type"])


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events per kind in windows of two days that start every day."""
    counted = events(spark, sf_dir).withWatermark("ts", "40000 days").groupBy(F.window("ts", "2 days", "1 day"), "event_type").agg(F.count("*").alias("cnt"))
    flat = counted.select(F.unix_seconds("window.start").alias("window_start"), "event_type", "cnt")
    return run_to_end(flat, "update", ["window_start", "event_type"])


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of a user that end after six hours without an event; late rows are not cut off."""
    rows = events(spark, sf_dir).withWatermark("ts", "40000 days")
    counted = rows.groupBy(F.session_window("ts", "6 hours"), "user_id").agg(F.count("*").alias("cnt"))
    flat = counted.select("user_id", F.unix_micros("session_window.start").alias("session_start"), "cnt")
    # complete: a session that grew replaces its shorter form
    return run_to_end(flat, "complete", ["user_id", "session_start"])


def supports(spark: SparkSession, sf_dir: str, sets: list[list[str]]) -> DataFrame:
    """(window_start, items, support): baskets are a user's kinds of events on a day; supports of fixed itemsets per day.

    First the baskets per (day, user), then the supports per day, in one stateful aggregation and one stateless one per batch.
    """
    wanted = F.broadcast(spark.createDataFrame([(s,) for s in sets], "items array<string>"))
    rows = events(spark, sf_dir).withWatermark("ts", "40000 days")
    baskets = rows.groupBy(F.window("ts", "1 day"), "user_id").agg(F.collect_set("event_type").alias("basket"))
    flat = baskets.select(F.unix_seconds("window.start").alias("window_start"), "user_id", "basket")
    final = run_to_end(flat, "update", ["window_start", "user_id"])
    held = final.join(wanted, contains_all(F.col("basket"), F.col("items")))
    return held.groupBy("window_start", F.array_join("items", " ").alias("items")).agg(F.count("*").alias("support"))


class _Dropped(StreamingQueryListener):
    """Rows that each batch of one stream dropped, whatever the number of batches (a query itself keeps its last reports only)."""

    def __init__(self, name: str) -> None:
        self.name, self.id, self.batches, self.ended = name, None, {}, threading.Event()

    def onQueryStarted(self, event) -> None:
        if event.name == self.name:
            self.id = event.id

    def onQueryProgress(self, event) -> None:
        p = event.progress
        if p.name == self.name:
            self.batches[p.batchId] = sum(s.numRowsDroppedByWatermark for s in p.stateOperators)

    def onQueryIdle(self, event) -> None:
        pass

    def onQueryTerminated(self, event) -> None:
        if event.id == self.id:
            self.ended.set()


def late_rows(spark: SparkSession, sf_dir: str, delay: str = "1 hour") -> DataFrame:
    """(batch, dropped): rows that came after the watermark had passed their window, from the stream's own progress."""
    counted = events(spark, sf_dir, 1).withWatermark("ts", delay).groupBy(F.window("ts", "1 hour")).count()
    folder = new_folder(spark, "late")
    heard = _Dropped(f"late-{uuid.uuid4().hex}")
    spark.streams.addListener(heard)
    try:
        query = counted.writeStream.queryName(heard.name).outputMode("append").format("noop").option("checkpointLocation", folder).trigger(availableNow=True).start()
        query.awaitTermination()
        # reports arrive in order, the end of the query last
        if not heard.ended.wait(600):
            raise TimeoutError("the end of the stream was not reported")
    finally:
        spark.streams.removeListener(heard)
    return spark.createDataFrame(sorted(heard.batches.items()), "batch long, dropped long")


def bounds_per_batch(spark: SparkSession, sf_dir: str, items: list[str], out: Callable[[DataFrame, int], None]) -> None:
    """For each batch the bounds of the itemset of all ``items`` from the supports of its subsets in that batch."""

    def take(batch: DataFrame, number: int) -> None:
        baskets = batch.groupBy("user_id").agg(F.collect_set("event_type").alias("held"))
        ids = F.array_compact(F.array(*[F.when(F.array_contains("held", name), F.lit(i)) for i, name in enumerate(items)]))
        masks = F.sequence(F.lit(0), F.call_function("shiftleft", F.lit(1), F.size("ids")) - 1)
        subsets = baskets.select(ids.alias("ids")).select("ids", F.explode(masks).alias("m")).select(F.filter("ids", lambda x, i: F.getbit("m", i) == 1).alias("items"))
        counts = subsets.groupBy("items").agg(F.count("*").alias("support"))
        every = batch.sparkSession.range(1 << len(items)).select(F.filter(F.array(*map(F.lit, range(len(items)))), lambda x: F.getbit("id", x) == 1).alias("items"))
        known = every.join(counts, "items", "left").select("items", F.coalesce("support", F.lit(0)).cast("long").alias("support"))
        whole = batch.sparkSession.range(1).select(F.array(*map(F.lit, range(len(items)))).alias("items"))
        out(rules.bounds(whole, known, len(items)), number)

    folder = new_folder(spark, "stream-bounds")
    events(spark, sf_dir).writeStream.foreachBatch(take).option("checkpointLocation", folder).trigger(availableNow=True).start().awaitTermination()


def running_supports(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_type, support, total): counts kept in a state of our own across batches."""

    def add(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0.0)
        for frame in frames:
            n, total = n + int(frame["n"].sum()), total + float(frame["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"event_type": [key[0]], "support": [n], "total": [total]})

    rows = events(spark, sf_dir).select("event_type", F.lit(1).cast("long").alias("n"), "value")
    counted = rows.groupBy("event_type").applyInPandasWithState(add, "event_type string, support long, total double", "n long, total double", "update", "NoTimeout")
    return run_to_end(counted, "update", ["event_type"]).select("event_type", "support", F.round("total", 4).alias("total"))


def with_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stream joined with a table: events with the market segment of the customer of that number."""
    customers = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return run_to_end(events(spark, sf_dir).join(customers, "user_id", "left").select("event_id", "c_mktsegment"))


def follow_ups(spark: SparkSession, sf_dir: str, first: str, second: str) -> DataFrame:
    """Stream joined with stream: an event of one kind and another within the hour after it, by the same user."""
    rows = events(spark, sf_dir).withWatermark("ts", "40000 days").select("event_id", "user_id", "event_type", "ts")
    a = rows.where(F.col("event_type") == first).select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").alias("ta"))
    b = rows.where(F.col("event_type") == second).select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").alias("tb"))
    return run_to_end(a.join(b, F.expr("ua = ub AND tb >= ta AND tb <= ta + INTERVAL 1 HOUR")).select("a", "b"))


def distinct_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stream without repeats: each (user, kind) once."""
    rows = events(spark, sf_dir).withWatermark("ts", "40000 days")
    return run_to_end(rows.dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type"))


def stream_supports(spark: SparkSession, sf_dir: str) -> DataFrame:
    kinds = [r[0] for r in spark.read.parquet(f"{sf_dir}/events.parquet").select("event_type").distinct().orderBy("event_type").collect()]
    return supports(spark, sf_dir, [kinds[:1], kinds[:2], kinds[1:4]])


def stream_follow_ups(spark: SparkSession, sf_dir: str) -> DataFrame:
    kinds = [r[0] for r in spark.read.parquet(f"{sf_dir}/events.parquet").select("event_type").distinct().orderBy("event_type").limit(2).collect()]
    return follow_ups(spark, sf_dir, *kinds)


def stream_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bounds on users with the first three kinds of events, from the supports of the smaller sets."""
    kinds = [r[0] for r in spark.read.parquet(f"{sf_dir}/events.parquet").select("event_type").distinct().orderBy("event_type").limit(3).collect()]
    folder = new_folder(spark, "bounds-out")
    bounds_per_batch(spark, sf_dir, kinds, lambda df, n: df.write.mode("overwrite").parquet(f"{folder}/batch={n}"))
    return spark.read.parquet(folder).select(F.col("batch").cast("long").alias("batch"), "lower", "upper")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "stream_tumbling": tumbling,
    "stream_sliding": sliding,
    "stream_session": sessions,
    "stream_supports": stream_supports,
    "stream_late": late_rows,
    "stream_bounds": stream_bounds,
    "stream_running_supports": running_supports,
    "stream_static_join": with_segments,
    "stream_follow_ups": stream_follow_ups,
    "stream_dedup": distinct_users,
}
_KINDS = "k AS (SELECT list(DISTINCT event_type ORDER BY event_type) AS kinds FROM events)"
ORACLES: dict[str, str] = {
    "stream_tumbling": "SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS window_start, event_type, count(*) AS cnt FROM events GROUP BY 1, 2",
    "stream_sliding": "SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) - 86400 * o AS window_start, event_type, count(*) AS cnt FROM events, (VALUES (0), (1)) x(o) GROUP BY 1, 2",
    "stream_session": """WITH g AS (SELECT *, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER w < 21600000000 THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS session FROM g) SELECT user_id, epoch_us(min(ts)) AS session_start, count(*) AS cnt FROM s GROUP BY user_id, session""",
    "stream_supports": f"""WITH {_KINDS}, w AS (SELECT unnest([kinds[1:1], kinds[1:2], kinds[2:4]]) AS items FROM k),
b AS (SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS window_start, user_id, list(DISTINCT event_type) AS basket FROM events GROUP BY 1, 2)
SELECT window_start, array_to_string(items, ' ') AS items, count(*) AS support FROM b JOIN w ON list_has_all(basket, items) GROUP BY 1, 2""",
    "stream_running_supports": "SELECT event_type, count(*) AS support, round(sum(value), 4) AS total FROM events GROUP BY 1",
    "stream_static_join": "SELECT event_id, c_mktsegment FROM events LEFT JOIN customer ON user_id = c_custkey",
    "stream_follow_ups": """WITH k AS (SELECT DISTINCT event_type FROM events ORDER BY 1 LIMIT 2) SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND epoch_us(b.ts) - epoch_us(a.ts) BETWEEN 0 AND 3600000000
WHERE a.event_type = (SELECT min(event_type) FROM k) AND b.event_type = (SELECT max(event_type) FROM k)""",
    "stream_dedup": "SELECT DISTINCT user_id, event_type FROM events",
    "stream_bounds": """WITH k AS (SELECT list(DISTINCT event_type ORDER BY event_type) AS kinds FROM events),
m AS (SELECT user_id, max(CAST(event_type = kinds[1] AS INT)) AS a, max(CAST(event_type = kinds[2] AS INT)) AS b, max(CAST(event_type = kinds[3] AS INT)) AS c FROM events, k GROUP BY 1),
s AS (SELECT CAST(count(*) AS BIGINT) AS n, CAST(sum(a) AS BIGINT) AS a, CAST(sum(b) AS BIGINT) AS b, CAST(sum(c) AS BIGINT) AS c, CAST(sum(a * b) AS BIGINT) AS ab, CAST(sum(a * c) AS BIGINT) AS ac, CAST(sum(b * c) AS BIGINT) AS bc FROM m)
SELECT CAST(0 AS BIGINT) AS batch, greatest(0, ab + ac - a, ab + bc - b, ac + bc - c) AS lower, least(ab, ac, bc, ab + ac + bc - a - b - c + n) AS upper FROM s""",
}
