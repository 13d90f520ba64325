"""Supports of given itemsets: one pass over the encoded baskets, whatever the number of itemsets.

Strategies (all exact, equal results):

* ``mask``        baskets and itemsets as bits of one integer, broadcast itemsets; up to 62 items
* ``expand``      the k-subsets of each basket, counted map-side, then looked up; short baskets
* ``trie``        a prefix tree of broadcast itemsets walked by each basket, counts kept per task
* ``bitmap``      bitmaps of baskets for each (item, block), ANDed with one for each bit of the weights; few items, many baskets
* ``pattern``     distinct projected baskets with weights, containment test against broadcast itemsets
* ``scan``        containment test of every basket and itemset; the reference
* ``partitioned`` itemsets and baskets meet on the itemset's rarest item and a salt; no broadcast, any number of itemsets
"""

from __future__ import annotations

from collections.abc import Iterator
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supportbounds.operators.baskets import MASK_ITEMS, Database, numbered
from supportbounds.operators.itemsets import contains_all, k_subsets
from supportbounds.plans.workspace import keep, small

#: Itemsets up to this number are broadcast (about 64 bytes each); beyond it they are joined.
BROADCAST_SETS = 500_000
#: Tests of a basket against an itemset that ``mask`` may take; beyond, baskets look their own subsets up.
MASK_TESTS = 2_000_000_000
#: Parts that the baskets of one item are split into.
SALTS = 8
STRATEGIES = ("mask", "expand", "trie", "bitmap", "pattern", "scan", "partitioned")


def of(db: Database, items: list[int]) -> int:
    """Support of one itemset of ids."""
    wanted = F.array(*map(F.lit, items)) if items else F.array().cast("array<int>")
    return db.baskets.where(contains_all(F.col("items"), wanted)).agg(F.coalesce(F.sum("weight"), F.lit(0))).first()[0]


def cover(baskets: DataFrame, items: list) -> DataFrame:
    """Ids of the baskets of a view that hold all ``items``."""
    return baskets.where(contains_all(F.col("items"), F.array(*map(F.lit, items)))).select("basket_id")


def frequent(supports: DataFrame, threshold: int, strict: bool = False) -> DataFrame:
    return supports.where(F.col("support") > threshold if strict else F.col("support") >= threshold)


def choose(db: Database, n_sets: int, k: int) -> str:
    """The strategy for ``n_sets`` itemsets of size ``k``: by what is broadcast and by the work per basket."""
    if n_sets > BROADCAST_SETS:
        return "partitioned"
    longest, rows = db.baskets.agg(F.max(F.size("items")), F.count("*")).first()
    longest = longest or 0
    if db.n_items <= MASK_ITEMS and n_sets * rows <= MASK_TESTS:
        return "mask"
    return "expand" if comb(longest, k) <= 5000 else "trie"


def count(db: Database, sets: DataFrame, k: int, strategy: str = "auto", n_sets: int | None = None) -> DataFrame:
    """(items, support) for every row of ``sets`` (distinct, all of size ``k`` >= 1); sets in no basket have support 0."""
    if strategy == "auto":
        strategy = choose(db, sets.count() if n_sets is None else n_sets, k)
    found = {"mask": _mask, "expand": _expand, "trie": _trie, "bitmap": _bitmap, "pattern": _pattern, "scan": _scan, "partitioned": _partitioned}[strategy](db, sets.select("items"), k)
    return sets.select("items").join(found, "items", "left").withColumn("support", F.coalesce("support", F.lit(0)).cast("long"))


def _mask(db: Database, sets: DataFrame, k: int) -> DataFrame:
    bits = F.aggregate("items", F.lit(0).cast("long"), lambda a, i: a.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), i)))
    wanted = F.broadcast(sets.select("items", bits.alias("w")))
    held = db.masks().join(wanted, F.col("mask").bitwiseAND(F.col("w")) == F.col("w"))
    return held.groupBy("items").agg(F.sum("weight").alias("support"))


def _expand(db: Database, sets: DataFrame, k: int) -> DataFrame:
    long_enough = db.baskets.where(F.size("items") >= k)
    subsets = long_enough.select(F.explode(k_subsets(F.col("items"), k)).alias("items"), "weight")
    # what nobody asked for goes before anything is moved
    return subsets.join(small(sets), "items", "left_semi").groupBy("items").agg(F.sum("weight").alias("support"))


def _trie(db: Database, sets: DataFrame, k: int) -> DataFrame:
    wanted = sorted(tuple(r.items_) for r in sets.select(F.col("items").alias("items_")).collect())  # choose() bounds their number
    shared = db.baskets.sparkSession.sparkContext.broadcast(np.array(wanted, dtype=np.int32).reshape(-1, k))

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        root: dict = {}
        for number, path in enumerate(shared.value.tolist()):
            node = root
            for item in path[:-1]:
                node = node.setdefault(item, {})
            node[path[-1]] = number
        counts = np.zeros(len(shared.value), dtype=np.int64)

        def visit(node: dict, basket: list[int], start: int, depth: int, weight: int) -> None:
            for i in range(start, len(basket) - (k - depth) + 1):
                child = node.get(basket[i])
                if child is not None:
                    if depth == k - 1:
                        counts[child] += weight
                    else:
                        visit(child, basket, i + 1, depth + 1, weight)

        for batch in batches:
            for basket, weight in zip(batch.column("items").to_pylist(), batch.column("weight").to_pylist(), strict=True):
                visit(root, basket, 0, 0, weight)
        seen = np.flatnonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(seen), pa.array(counts[seen])], names=["n", "c"])

    sums = db.baskets.where(F.size("items") >= k).select("items", "weight").mapInArrow(walk, "n long, c long").groupBy("n").agg(F.sum("c").alias("support"))

    def name(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = shared.value[batch.column("n").to_numpy()]
            yield pa.RecordBatch.from_arrays([pa.array(rows.tolist(), pa.list_(pa.int32())), batch.column("support")], names=["items", "support"])

    return sums.mapInArrow(name, "items array<int>, support long")


def vertical(db: Database) -> tuple[DataFrame, DataFrame]:
    """(item, block, bits): bitmaps of the merged baskets' numbers; (block, power, bits): the baskets whose weight has that power of two."""
    single = keep(db.baskets.select("items", "weight", F.monotonically_increasing_id().alias("b")), "numbered")
    place = F.bitmap_construct_agg(F.bitmap_bit_position("b")).alias("bits")
    block = F.bitmap_bucket_number("b").alias("block")
    bits = single.select(F.explode("items").alias("item"), "b").groupBy("item", block).agg(place)
    powers = F.filter(F.sequence(F.lit(0), F.lit(62)), lambda p: F.getbit("weight", p) == 1)
    planes = single.select(F.explode(powers).alias("power"), "b").groupBy(block, "power").agg(place)
    return bits, planes


def _bitmap(db: Database, sets: DataFrame, k: int) -> DataFrame:
    bits, planes = vertical(db)
    parts = sets.select("items", F.explode("items").alias("item")).join(bits, "item")
    both = parts.groupBy("items", "block").agg(F.bitmap_and_agg("bits").alias("bits"), F.count("*").alias("n")).where(F.col("n") == k)
    weighed = both.select("items", "block", "bits").join(planes.withColumnRenamed("bits", "plane"), "block")
    pairs = weighed.select("items", "block", "power", F.explode(F.array("bits", "plane")).alias("bits"))
    ones = pairs.groupBy("items", "block", "power").agg(F.bitmap_count(F.bitmap_and_agg("bits")).alias("n"))
    return ones.groupBy("items").agg(F.sum(F.call_function("shiftleft", F.col("n"), F.col("power"))).alias("support"))


def _pattern(db: Database, sets: DataFrame, k: int) -> DataFrame:
    used = sets.select(F.explode("items").alias("i")).agg(F.collect_set("i").alias("used"))  # one row, a dictionary's length at most
    cut = db.baskets.join(F.broadcast(used)).select(F.array_intersect("items", "used").alias("b"), "weight").groupBy("b").agg(F.sum("weight").alias("weight"))
    return cut.join(F.broadcast(sets), contains_all(F.col("b"), F.col("items"))).groupBy("items").agg(F.sum("weight").alias("support"))


def _scan(db: Database, sets: DataFrame, k: int) -> DataFrame:
    rows = db.baskets.select(F.col("items").alias("b"), "weight")
    return rows.join(F.broadcast(sets), contains_all(F.col("b"), F.col("items"))).groupBy("items").agg(F.sum("weight").alias("support"))


def _partitioned(db: Database, sets: DataFrame, k: int) -> DataFrame:
    # ids go from frequent to rare, so the last item is the rarest: the fewest baskets meet there
    keyed = sets.select(F.element_at("items", -1).alias("rarest"), F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"), "items")
    rarest = sets.select(F.element_at("items", -1).alias("rarest")).distinct()
    salt = F.pmod(F.xxhash64("items"), F.lit(SALTS)).cast("int").alias("salt")
    rows = db.baskets.where(F.size("items") >= k).select(F.explode(F.slice("items", k, F.size("items"))).alias("rarest"), salt, F.col("items").alias("b"), "weight")
    rows = rows.join(small(rarest), "rarest", "left_semi")
    return rows.join(keyed, ["rarest", "salt"]).where(contains_all(F.col("b"), F.col("items"))).groupBy("items").agg(F.sum("weight").alias("support"))


def pairs(db: Database, items: DataFrame) -> DataFrame:
    """(items, support) of every pair of the given items (item_id) that some basket holds, counted from the baskets: no candidates are made."""
    wanted = small(items.select(F.col("item_id").alias("i")))
    rows = numbered(db.baskets.where(F.size("items") > 1), "b").select("b", "weight", F.explode("items").alias("i")).join(wanted, "i", "left_semi")
    cut = rows.groupBy("b", "weight").agg(F.array_sort(F.collect_list("i")).alias("items")).where(F.size("items") > 1)
    # one first item of a pair at a time, so that a long basket is no long array
    firsts = cut.select("items", "weight", F.posexplode("items").alias("at", "a"))
    found = firsts.select("a", F.explode(F.slice("items", F.col("at") + 2, F.size("items"))).alias("b"), "weight")
    return found.groupBy("a", "b").agg(F.sum("weight").alias("support")).select(F.array("a", "b").alias("items"), "support")
