"""Variable-capacity best-fit packing of sequences.

Several sequence lengths (bin sizes) are permitted, each with a cost, and optimised jointly: whenever a bin is opened for the
longest piece left, each size is filled best-fit from what is left (the longest piece that still fits, again and again) and cut down to the smallest size that
holds its contents; the size with the least cost for each token held is opened, as often as the pieces last. Plans that always open one preferred size
and put pieces into the open bin with the least room are made too, and the cheapest plan is taken.

The plan depends on the histogram of lengths alone, which has at most as many rows as the largest size has
positions. It is made on that histogram: equal bins are handled as one run of bin numbers, so a
plan over 10^10 pieces is as long as one over 10^5. Pieces are then numbered within their length, by a
two-level count that splits even one hot length over many tasks, and look their bin up in the plan.
"""

from __future__ import annotations

import bisect
from collections.abc import Iterator, Mapping, Sequence
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from supportbounds.llm.common import keep, text_of

SIZES = (512, 1024, 2048, 4096, 8192)


def default_cost(size: int) -> float:
    """A fixed part per sequence, a linear part and a part that grows with the square (attention)."""
    return 64.0 + size + size * size / 16384.0


@dataclass
class Plan:
    """Runs of bins. ``placed``: (length, first rank, count, first bin, start in the bin); ``bins``: (first bin, count, used, size)."""

    placed: list[tuple[int, int, int, int, int]] = field(default_factory=list)
    bins: list[tuple[int, int, int, int]] = field(default_factory=list)
    cost: float = 0.0


def plan(histogram: Mapping[int, int], sizes: Sequence[int] = SIZES, cost=default_cost) -> Plan:
    """The cheapest of the joint plan and those for each preferred size; ``histogram`` maps lengths (1 to the largest size) to counts."""
    sizes = sorted(sizes)
    return min([_joint_plan(histogram, sizes, cost), *(_plan_for(histogram, sizes, preferred, cost) for preferred in sizes)], key=lambda p: p.cost)


def _filling(lengths: list[int], left: Mapping[int, int], size: int) -> list[tuple[int, int]]:
    """(length, how many) of a bin of this size that takes the longest piece that fits, again and again; ``lengths`` rise."""
    room, found, k = size, [], len(lengths) - 1
    while (k := min(k, bisect.bisect_right(lengths, room) - 1)) >= 0:
        take = min(left[lengths[k]], room // lengths[k])
        found.append((lengths[k], take))
        room -= take * lengths[k]
        k -= 1
    return found


def _joint_plan(histogram: Mapping[int, int], sizes: list[int], cost) -> Plan:
    out, left, next_bin = Plan(), {n: c for n, c in histogram.items() if c}, 0
    lengths, rank = sorted(left), dict.fromkeys(left, 0)
    while lengths:
        choices = []
        for size in (s for s in sizes if s >= lengths[-1]):
            content = _filling(lengths, left, size)
            used = sum(n * t for n, t in content)
            fitted = next(s for s in sizes if s >= used)
            choices.append((cost(fitted) / used, size, fitted, used, content))
        _, _, fitted, used, content = min(choices)
        count, start = min(left[n] // t for n, t in content), 0
        for n, t in content:
            for _ in range(t):
                out.placed.append((n, rank[n], count, next_bin, start))
                rank[n] += count
                start += n
            left[n] -= count * t
            if not left[n]:
                del lengths[bisect.bisect_left(lengths, n)]
        out.bins.append((next_bin, count, used, fitted))
        out.cost += count * cost(fitted)
        next_bin += count
    out.placed.sort()
    return out


def _plan_for(histogram: Mapping[int, int], sizes: list[int], preferred: int, cost) -> Plan:
    out = Plan()
    runs: dict[int, list[tuple[int, int, int]]] = {}  # room -> runs (first bin, count, size)
    rooms: list[int] = []
    next_bin = 0

    def add(room: int, run: tuple[int, int, int]) -> None:
        if room not in runs:
            runs[room] = []
            bisect.insort(rooms, room)
        runs[room].append(run)

    for length in sorted(histogram, reverse=True):
        left, rank = histogram[length], 0
        while left:
            k = bisect.bisect_left(rooms, length)
            if k < len(rooms):
                room = rooms[k]
                first, count, size = runs[room].pop()
                take = min(count, left)
                if take < count:
                    runs[room].append((first + take, count - take, size))
                if not runs[room]:
                    del runs[room], rooms[k]
                out.placed.append((length, rank, take, first, size - room))
                add(room - length, (first, take, size))
                rank, left = rank + take, left - take
                continue
            size = preferred if preferred >= length else min((s for s in sizes if s >= length), key=cost)
            fit = size // length
            # bins that this length fills alone, all at once; what is left over opens one more
            for count, each in ((left // fit, fit), (1, left % fit)):
                if count and each:
                    for i in range(each):
                        out.placed.append((length, rank, count, next_bin, i * length))
                        rank += count
                    add(size - each * length, (next_bin, count, size))
                    next_bin += count
            left = 0
    for room, held in runs.items():
        for first, count, size in held:
            fitted = next(s for s in sizes if s >= size - room)
            out.bins.append((first, count, size - room, fitted))
            out.cost += count * cost(fitted)
    out.placed.sort()
    out.bins.sort()
    return out


def word_lengths(docs: DataFrame, text: str = "text") -> Column:
    """Words of the whole text and one end mark."""
    return F.regexp_count(text_of(docs, text), F.lit(r"[^\x20\x09-\x0D]+")) + 1


def pieces(docs: DataFrame, length: Column, largest: int, key: str = "doc_id") -> DataFrame:
    """(key, row, piece, n_tokens): documents longer than the largest size in full pieces and a rest; nothing is cut off."""
    rows = docs.select(F.col(key).alias("key"), F.monotonically_increasing_id().alias("row"), F.greatest(F.coalesce(length, F.lit(0)), F.lit(1)).cast("long").alias("all"))
    rows = keep(rows, "lengths")
    numbered = rows.select("*", F.explode(F.sequence(F.lit(0), F.floor((F.col("all") - 1) / largest).cast("int"))).alias("piece"))
    return numbered.select("key", "row", "piece", F.least(F.lit(largest), F.col("all") - F.col("piece").cast("long") * largest).cast("int").alias("n_tokens"))


def _ranked(items: DataFrame) -> DataFrame:
    """Adds the rank of each piece among those of its length: counts per (length, salt), then places within the salt."""
    salts = int(items.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    salted = items.withColumn("salt", F.pmod(F.xxhash64("row", "piece"), F.lit(salts)).cast("int"))
    counts = salted.groupBy("n_tokens", "salt").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("n_tokens").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = counts.select("n_tokens", "salt", before.alias("before"))
    place = F.row_number().over(Window.partitionBy("n_tokens", "salt").orderBy("row", "piece")) - 1
    return salted.withColumn("place", place).join(offsets, ["n_tokens", "salt"]).withColumn("rank", F.col("before") + F.col("place"))


def _placed(items: DataFrame, sizes: Sequence[int], cost) -> DataFrame:
    """``items`` (key, row, piece, n_tokens) with bin_id, bin_size and start."""
    spark = items.sparkSession
    histogram = {r.n_tokens: r.n for r in items.groupBy("n_tokens").agg(F.count("*").alias("n")).collect()}  # max(sizes) rows at most
    found = plan(histogram, sizes, cost)
    placed = np.array(found.placed, dtype=np.int64).reshape(-1, 5)
    bins = np.array(found.bins, dtype=np.int64).reshape(-1, 4)
    shared = spark.sparkContext.broadcast(((placed[:, 0] << 44) + placed[:, 1], placed, bins))

    def look_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        starts, placed, bins = shared.value
        for batch in batches:
            n, rank = batch.column("n_tokens").to_numpy().astype(np.int64), batch.column("rank").to_numpy()
            run = placed[np.searchsorted(starts, (n << 44) + rank, side="right") - 1]
            bin_id = run[:, 3] + rank - run[:, 1]
            size = bins[np.searchsorted(bins[:, 0], bin_id, side="right") - 1, 3]
            own = [batch.column(c) for c in ("key", "row", "piece", "n_tokens")]
            yield pa.RecordBatch.from_arrays([*own, pa.array(bin_id), pa.array(size.astype(np.int32)), pa.array(run[:, 4].astype(np.int32))], names=["key", "row", "piece", "n_tokens", "bin_id", "bin_size", "start"])

    ranked = _ranked(items).select("key", "row", "piece", "n_tokens", "rank")
    kind = ranked.schema["key"].dataType.simpleString()
    return ranked.mapInArrow(look_up, f"key {kind}, row long, piece int, n_tokens int, bin_id long, bin_size int, start int")


def pack(docs: DataFrame, length: Column | None = None, sizes: Sequence[int] = SIZES, cost=default_cost, text: str = "text", key: str = "doc_id") -> DataFrame:
    """key, piece, n_tokens, bin_id, bin_size, start for every piece of every row.

    ``length``: tokens of a row (default: its words and an end mark; no tokenizer is run); null or less than one counts as one, so a null or empty
    text is one piece of one token. Rows are packed one by one, repeated ones too; null keys are kept; texts of any length are cut into pieces, none is
    shortened; pieces of equal length are placed in the order of the rows as read; of plans of equal cost the joint one is taken; further columns do not matter;
    an empty table gives an empty result.
    """
    items = pieces(docs, word_lengths(docs, text) if length is None else length, max(sizes), key)
    return _placed(items, sizes, cost).drop("row").withColumnRenamed("key", key)


def sequences(docs: DataFrame, ids: str = "ids", sizes: Sequence[int] = SIZES, cost=default_cost, pad_id: int = 0, key: str = "doc_id") -> DataFrame:
    """bin_id, bin_size, tokens (padded to the bin's size), pieces (key, piece, start, n_tokens): the packed sequences of token ids.

    Rows with null or empty ids hold no tokens and are left out.
    """
    rows = keep(docs.where(F.size(ids) > 0).select(F.col(key).alias("key"), F.monotonically_increasing_id().alias("row"), F.col(ids).cast("array<int>").alias("ids")), "token-rows")
    largest = max(sizes)
    cut = rows.select("key", "row", F.explode(F.sequence(F.lit(0), F.floor((F.size("ids") - 1) / largest).cast("int"))).alias("piece"), F.size("ids").alias("all"))
    items = cut.select("key", "row", "piece", F.least(F.lit(largest), F.col("all") - F.col("piece") * largest).cast("int").alias("n_tokens"))
    placed = _placed(keep(items, "token-pieces"), sizes, cost).drop("key").join(rows, "row")
    part = F.slice("ids", F.col("piece") * largest + 1, F.col("n_tokens"))
    held = placed.select("bin_id", "bin_size", F.struct("start", F.col("key").alias(key), "piece", "n_tokens", part.alias("part")).alias("x"))
    bins = held.groupBy("bin_id", "bin_size").agg(F.array_sort(F.collect_list("x")).alias("x"))  # a bin holds its size at most
    filled = F.flatten(F.transform("x", lambda x: x["part"]))
    padded = F.concat(filled, F.array_repeat(F.lit(pad_id), F.col("bin_size") - F.size(filled)))
    return bins.select("bin_id", "bin_size", padded.alias("tokens"), F.transform("x", lambda x: F.struct(x[key].alias(key), x["piece"].alias("piece"), x["start"].alias("start"), x["n_tokens"].alias("n_tokens"))).alias("pieces"))
