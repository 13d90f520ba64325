"""Fractions: how many baskets consist, within J, of exactly I; and databases built from them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supportbounds.operators import rules
from supportbounds.operators.baskets import Database
from supportbounds.operators.itemsets import contains_all, empty, pick


def _projected(db: Database, j: list[int]) -> DataFrame:
    return db.baskets.select(F.array_intersect("items", F.array(*map(F.lit, j)) if j else empty()).alias("base"), "weight")


def of(db: Database, i: list[int], j: list[int]) -> int:
    wanted = F.array(*map(F.lit, i)) if i else empty()
    return _projected(db, j).where(F.col("base") == wanted).agg(F.coalesce(F.sum("weight"), F.lit(0))).first()[0]


def table(db: Database, j: list[int]) -> DataFrame:
    """(base, cnt) for all subsets of J, those without a basket too."""
    whole = F.array(*map(F.lit, j)) if j else empty()
    cells = db.baskets.sparkSession.range(1 << len(j)).select(pick(whole, F.col("id")).alias("base"))
    counts = _projected(db, j).groupBy("base").agg(F.sum("weight").alias("cnt"))
    return cells.join(counts, "base", "left").select("base", F.coalesce("cnt", F.lit(0)).cast("long").alias("cnt"))


def to_supports(cells: DataFrame) -> DataFrame:
    """(items, support): the sum of the fractions of all supersets within J."""
    over = cells.select(F.col("base").alias("over"), "cnt")
    return cells.select(F.col("base").alias("items")).join(over, contains_all(F.col("over"), F.col("items"))).groupBy("items").agg(F.sum("cnt").alias("support"))


def witness(sets: DataFrame, supports: DataFrame, n: int, value) -> DataFrame:
    """(items, basket, weight): for each J a database in which every proper subset has its given support and J has ``value``.

    The cell of a base I is (-1)^|J - I| * (value - sigma(I, J)); the cell of J itself is ``value``. All cells are
    non-negative exactly when the value is within the bounds, which makes the bounds tight.
    """
    ruled = rules.explain(sets, supports, n).join(value, "items")
    sign = F.when(F.col("depth") % 2 == 0, 1).otherwise(-1)
    cells = ruled.select("items", F.col("base").alias("basket"), F.when(F.col("depth") == 0, F.col("v")).otherwise(sign * (F.col("v") - F.col("sigma"))).cast("long").alias("weight"))
    return cells


def covers(db: Database, base: list[int], others: list[int]) -> DataFrame:
    """One row: size of the union of the covers of base + {a} over ``others``, and the cover of the base less its fraction."""
    hold = F.col("items")
    whole = contains_all(hold, F.array(*map(F.lit, base)) if base else empty())
    some = F.arrays_overlap(hold, F.array(*map(F.lit, others)))
    rows = db.baskets.where(whole)
    total = F.coalesce(F.sum("weight"), F.lit(0))
    return rows.agg(F.coalesce(F.sum(F.when(some, F.col("weight"))), F.lit(0)).alias("union_size"), (total - F.coalesce(F.sum(F.when(~some, F.col("weight"))), F.lit(0))).alias("support_minus_fraction"))
