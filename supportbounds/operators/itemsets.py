"""Expressions on itemsets (sorted arrays of ids)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

EMPTY = "array<int>"


def empty() -> Column:
    return F.array().cast(EMPTY)


def pick(items: Column, mask: Column) -> Column:
    """The items at the positions whose bits are set in ``mask``."""
    return F.filter(items, lambda x, i: F.getbit(mask, i) == 1)


def immediate_subsets(items: Column) -> Column:
    """The sets with one item less, as (dropped, rest)."""
    return F.transform(items, lambda x: F.struct(x.alias("dropped"), F.array_remove(items, x).alias("rest")))


def contains_all(big: Column, part: Column) -> Column:
    return F.size(F.array_except(part, big)) == 0


def contains_any(big: Column, part: Column) -> Column:
    return F.arrays_overlap(big, part)


def contains_none(big: Column, part: Column) -> Column:
    return ~F.arrays_overlap(big, part)


def same_items(one: Column, other: Column) -> Column:
    return F.array_sort(F.array_distinct(one)) == F.array_sort(F.array_distinct(other))


def k_subsets(items: Column, k: int) -> Column:
    """All sorted subsets of size ``k`` of a sorted array."""
    if k == 0:
        return F.array(empty())
    found = F.transform(items, lambda x: F.array(x))
    for _ in range(k - 1):
        found = F.flatten(F.transform(found, _longer(items)))
    return found


def _longer(items: Column):
    return lambda p: F.transform(F.filter(items, lambda x: x > F.element_at(p, -1)), lambda x: F.concat(p, F.array(x)))


def generate(sets: DataFrame, k: int) -> DataFrame:
    """Candidates of size ``k + 1`` all of whose subsets of size ``k`` are in ``sets`` (items).

    Sets with the same first ``k - 1`` items meet in one equi-join; the other subsets are then looked up.
    """
    left = sets.select(F.slice("items", 1, k - 1).alias("prefix") if k > 1 else F.lit(0).alias("prefix"), F.element_at("items", -1).alias("a"))
    right = left.withColumnRenamed("a", "b")
    joined = left.join(right, "prefix").where("a < b")
    pairs = F.array("a", "b")
    found = joined.select((F.concat("prefix", pairs) if k > 1 else pairs).alias("items"))
    if k == 1:
        return found
    # the two subsets without the last or the last but one item are there already
    others = found.select("items", F.explode(F.slice(immediate_subsets(F.col("items")), 1, k - 1)).alias("s")).select("items", F.col("s.rest").alias("rest"))
    held = others.join(sets.select(F.col("items").alias("rest")), "rest", "left_semi")
    return held.groupBy("items").agg(F.count("*").alias("n")).where(F.col("n") == k - 1).select("items")
