"""Checks of what theory promises; each returns the offending rows (none, if all is well)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supportbounds.operators import fractions, rules, support
from supportbounds.operators.baskets import Database, project
from supportbounds.operators.itemsets import immediate_subsets, k_subsets
from supportbounds.plans.levelwise import Run, _union


def unsound(bounds: DataFrame, supports: DataFrame) -> DataFrame:
    """Itemsets whose support lies outside their interval."""
    return bounds.join(supports, "items").where((F.col("support") < F.col("lower")) | (F.col("support") > F.col("upper")))


def gap_differs(db: Database, sets: DataFrame, supports: DataFrame, j: list[int]) -> DataFrame:
    """Rules of J whose distance from the support is not the number of baskets that are exactly the base within J."""
    own = supports.where(F.col("items") == F.array(*map(F.lit, j)))
    ruled = rules.explain(sets, supports, len(j)).join(own.select("items", "support"), "items")
    cells = fractions.table(db, j)
    return ruled.where("depth > 0").join(cells, "base").where(F.abs(F.col("support") - F.col("sigma")) != F.col("cnt"))


def not_halved(bounds: DataFrame, supports: DataFrame) -> DataFrame:
    """Sets whose width is more than the distance of a subset's support to its nearer bound, or more than half of that subset's width."""
    sub = bounds.join(supports, "items").select(F.col("items").alias("rest"), F.least(F.col("support") - F.col("lower"), F.col("upper") - F.col("support")).alias("near"), (F.col("upper") - F.col("lower")).alias("below"))
    above = bounds.select("items", (F.col("upper") - F.col("lower")).alias("width"), F.explode(immediate_subsets(F.col("items"))).alias("x"))
    return above.select("items", "width", F.col("x.rest").alias("rest")).join(sub, "rest").where((F.col("width") > F.col("near")) | (2 * F.col("width") > F.col("below")))


def derivable_not_monotone(bounds: DataFrame) -> DataFrame:
    """Non-derivable sets with a derivable subset."""
    tight = bounds.where("lower = upper").select(F.col("items").alias("rest"))
    return bounds.where("lower <> upper").select("items", F.explode(immediate_subsets(F.col("items"))).alias("x")).select("items", F.col("x.rest").alias("rest")).join(tight, "rest", "left_semi")


def differing(one: DataFrame, other: DataFrame, columns: tuple[str, ...] = ("items", "support")) -> DataFrame:
    """Rows that one of two results has and the other has not."""
    a, b = one.select(*columns), other.select(*columns)
    return a.exceptAll(b).unionByName(b.exceptAll(a))


def too_long(run: Run, limit: int) -> DataFrame:
    return run.sets.where(F.col("k") > limit)


def projection_differs(db: Database, j: list[int]) -> DataFrame:
    """Subsets of J (items, support) whose support in the baskets cut down to J is another one than in the baskets."""
    spark = db.baskets.sparkSession
    cut = Database(project(db.baskets, j).groupBy("items").agg(F.sum("weight").alias("weight")), db.items, db.n_baskets, db.n_items)
    parts = []
    for k in range(1, len(j) + 1):
        sets = spark.range(1).select(F.explode(k_subsets(F.array(*map(F.lit, j)), k)).alias("items"))
        parts.append(differing(support.count(db, sets, k, "scan"), support.count(cut, sets, k, "scan")))
    return _union(parts)


def inclusion_exclusion(supports: DataFrame, j: list[int]) -> DataFrame:
    """(base, cnt): the fraction of each base within J, added up with alternating signs from the supports of its supersets within J."""
    whole = F.array(*map(F.lit, j))
    inside = supports.where(F.size(F.array_except("items", whole)) == 0).select(F.col("items").alias("over"), "support")
    bases = inside.select(F.col("over").alias("base"))
    sign = F.when((F.size("over") - F.size("base")) % 2 == 0, 1).otherwise(-1)
    pairs = bases.join(inside, F.size(F.array_except("base", "over")) == 0)  # 2^|J| sets on either side
    return pairs.groupBy("base").agg(F.sum(sign * F.col("support")).alias("cnt"))


def inherited_not_exact(bounds: DataFrame, supports: DataFrame) -> DataFrame:
    """Supersets (items, base) by one item of sets with an exact base X for which the rule of X or that of X and the new item misses the support.

    ``supports`` holds the empty set too.
    """
    known = bounds.join(supports, "items")
    exact = F.when(F.col("support") == F.col("lower"), F.col("lower_base")).when(F.col("support") == F.col("upper"), F.col("upper_base"))
    exact = known.select(F.col("items").alias("rest"), exact.alias("x")).where("x IS NOT NULL")
    above = bounds.select("items", F.explode(immediate_subsets(F.col("items"))).alias("s")).select("items", F.col("s.dropped").alias("i"), F.col("s.rest").alias("rest"))
    both = F.explode(F.array(F.col("x"), F.array_sort(F.concat("x", F.array("i"))))).alias("base")
    pairs = above.join(exact, "rest").select("items", both).distinct()
    return rules.single(pairs, supports).join(supports, "items").where("sigma <> support").select("items", "base")


def derived_not_counted(db: Database, derived: DataFrame) -> DataFrame:
    """Rows (items, support) of ``derived`` (items, k, support) whose support is not the one counted in the baskets, and the counted ones."""
    sizes = [r.k for r in derived.select("k").distinct().collect()]  # as many rows as sizes
    none = derived.select("items", "support").limit(0)
    return _union([none, *(differing(derived.where(F.col("k") == k), support.count(db, derived.where(F.col("k") == k).select("items"), k)) for k in sorted(sizes))])
