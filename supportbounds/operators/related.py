"""Related condensed representations, told from the supports of all frequent itemsets (items, support)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supportbounds.operators import rules
from supportbounds.operators.itemsets import generate, immediate_subsets
from supportbounds.plans.levelwise import _union, with_empty_set


def _below(frequent: DataFrame) -> DataFrame:
    return frequent.select("items", "support", F.explode(immediate_subsets(F.col("items"))).alias("x")).select("items", "support", F.col("x.rest").alias("rest"))


def free_sets(frequent: DataFrame, n_baskets: int) -> DataFrame:
    """No subset with one item less has the same support (no exact rule of depth 1)."""
    known = with_empty_set(frequent.select("items", "support"), n_baskets).select(F.col("items").alias("rest"), F.col("support").alias("s"))
    least = _below(frequent).join(known, "rest").groupBy("items", "support").agg(F.min("s").alias("least"))
    return least.where("least <> support").select("items", "support")


def disjunction_free(frequent: DataFrame, n_baskets: int, longest: int, max_depth: int | None = 2) -> DataFrame:
    """No rule of depth 1 to ``max_depth`` is exact; without a limit: the generalised form."""
    known = with_empty_set(frequent.select("items", "support"), n_baskets)
    parts = []
    for n in range(1, longest + 1):
        sized = frequent.where(F.size("items") == n)
        sums = rules.sigmas(sized, known, n, max_depth).join(sized.select("items", "support"), "items")
        exact = F.exists(F.slice("sigma", 1, (1 << n) - 1), lambda s: s == F.col("support"))
        parts.append(sums.where(~F.coalesce(exact, F.lit(False))).select("items", "support"))
    return _union(parts)


def closed_sets(frequent: DataFrame) -> DataFrame:
    """No frequent superset with one item more has the same support."""
    above = _below(frequent).groupBy("rest").agg(F.max("support").alias("most")).withColumnRenamed("rest", "items")
    return frequent.join(above, "items", "left").where("most IS NULL OR most <> support").select("items", "support")


def maximal_sets(frequent: DataFrame) -> DataFrame:
    """No frequent superset at all."""
    return frequent.join(_below(frequent).select(F.col("rest").alias("items")).distinct(), "items", "left_anti").select("items", "support")


def supports_from_closed(closed: DataFrame, wanted: DataFrame) -> DataFrame:
    """Supports of frequent itemsets from the closed ones: the largest among the closed supersets. They meet on the last item."""
    left = wanted.select("items", F.element_at("items", -1).alias("i"))
    right = closed.select(F.col("items").alias("over"), "support", F.explode("items").alias("i"))
    return left.join(right, "i").where(F.size(F.array_except("items", "over")) == 0).groupBy("items").agg(F.max("support").alias("support"))


def border(members: DataFrame, longest: int, singles: DataFrame) -> DataFrame:
    """The minimal itemsets outside ``members`` (a family closed under subsets) over the items of ``singles``: what a free-set summary needs beside its sets."""
    parts = [singles.select("items").join(members.select("items"), "items", "left_anti")]
    for k in range(1, longest + 1):
        gen = generate(members.where(F.size("items") == k).select("items"), k)
        parts.append(gen.join(members.select("items"), "items", "left_anti"))
    return _union(parts)
