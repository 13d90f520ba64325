"""Joins that Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def within(left: DataFrame, right: DataFrame, keys: list[str], start: str, at: str, length: int) -> DataFrame:
    """Rows of ``right`` with ``at`` in [start, start + length] of a row of ``left`` with equal keys.

    Time is cut into cells of that length; a left row meets two cells, so the join is an equi-join on keys and cell.
    """
    cells = left.withColumn("__cell", F.explode(F.array(F.floor(F.col(start) / length), F.floor(F.col(start) / length) + 1)))
    placed = right.withColumn("__cell", F.floor(F.col(at) / length))
    return cells.join(placed, [*keys, "__cell"]).where((F.col(at) >= F.col(start)) & (F.col(at) <= F.col(start) + length)).drop("__cell")


def as_of(left: DataFrame, right: DataFrame, keys: list[str], at: str, values: list[str]) -> DataFrame:
    """Each row of ``left`` with the values of the latest row of ``right`` that is not later; of rows at the same time the one with the largest values.

    Both sides go through one sort by key and time instead of a join with all earlier rows.
    """
    extra = [c for c in left.columns if c not in (*keys, at)]
    a = left.select(*keys, at, F.lit(1).alias("__side"), F.struct(*extra).alias("__row"), F.lit(None).cast(right.select(F.struct(*values).alias("v")).schema["v"].dataType).alias("__v"))
    b = right.select(*keys, at, F.lit(0).alias("__side"), F.lit(None).cast(a.schema["__row"].dataType).alias("__row"), F.struct(*values).alias("__v"))
    w = Window.partitionBy(*keys).orderBy(at, "__side", "__v").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn("__found", F.last("__v", ignorenulls=True).over(w))
    return both.where("__side = 1").select(*keys, at, *[F.col(f"__row.{c}").alias(c) for c in extra], *[F.col(f"__found.{c}").alias(c) for c in values])


def salted(left: DataFrame, right: DataFrame, keys: list[str], salts: int = 16, how: str = "inner") -> DataFrame:
    """Equi-join in which each key's rows of ``left`` are spread over ``salts`` tasks; the rows of ``right`` are copied to each of them.

    Both sides are shuffled: the optimiser's size of ``right`` leaves out the copies, so that it would broadcast far more than it allows.
    """
    a = left.withColumn("__salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int"))
    b = right.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b.hint("merge"), [*keys, "__salt"], how).drop("__salt")


def similar_sets(sets: DataFrame, key: str, items: str, percent: int) -> DataFrame:
    """(a, b, shared) of all pairs of rows, a < b, whose sets (sorted arrays, rare items last) have a Jaccard similarity of ``percent`` or more.

    Two such sets share an item among the last ``n - ceil(share n) + 1`` of each; pairs that do are compared in full.
    """
    n = F.size(items)
    prefix = F.when(n > 0, F.slice(items, F.ceil(n * percent / 100).cast("int"), n)).otherwise(F.array().cast(sets.schema[items].dataType))
    rows = sets.select(F.col(key).alias("k"), F.col(items).alias("s"), F.explode(prefix).alias("i"))
    a, b = rows.select("i", F.col("k").alias("a"), F.col("s").alias("sa")), rows.select("i", F.col("k").alias("b"), F.col("s").alias("sb"))
    near = a.join(b, "i").where((F.col("a") < F.col("b")) & (100 * F.least(F.size("sa"), F.size("sb")) >= percent * F.greatest(F.size("sa"), F.size("sb"))))
    shared = F.size(F.array_intersect("sa", "sb"))
    found = near.dropDuplicates(["a", "b"]).withColumn("shared", shared)
    return found.where(100 * F.col("shared") >= percent * (F.size("sa") + F.size("sb") - F.col("shared"))).select("a", "b", "shared")
