"""The representation as a saved table, and its refresh."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from supportbounds.operators.baskets import Database
from supportbounds.operators.itemsets import contains_all, contains_none
from supportbounds.plans.levelwise import SET_SCHEMA, Run, mine


def classify(bounds: DataFrame) -> DataFrame:
    """Adds ``derivable``: both bounds are equal."""
    return bounds.withColumn("derivable", F.col("lower") == F.col("upper"))


def save(run: Run, path: str) -> None:
    """Sets by size, the dictionary, and one row of facts; the baskets are not saved."""
    run.sets.write.partitionBy("k").parquet(f"{path}/sets")
    run.db.items.write.parquet(f"{path}/items")
    depth = F.lit(run.max_depth).cast("int").alias("max_depth")
    run.sets.sparkSession.range(1).select(F.lit(run.db.n_baskets).alias("n_baskets"), F.lit(run.min_support).alias("min_support"), depth, F.lit(1).alias("version")).write.parquet(f"{path}/facts")


def load(spark: SparkSession, path: str) -> Run:
    """A saved representation; everything that needs no baskets works on it."""
    facts = spark.read.parquet(f"{path}/facts").first()
    items = spark.read.parquet(f"{path}/items")
    names = [c.split()[0] for c in SET_SCHEMA.split(", ")]
    sets = spark.read.parquet(f"{path}/sets").select(*names)
    db = Database(spark.createDataFrame([], "items array<int>, weight long"), items, facts.n_baskets, items.count())
    return Run(db, facts.min_support, facts.max_depth, sets, sets.select("items", "k", "lower", "upper"))


def select(
    sets: DataFrame, must: list[int] = (), without: list[int] = (), min_size: int = 1, max_size: int | None = None, min_support: int = 1, max_support: int | None = None, max_width: int | None = None
) -> DataFrame:
    """The sets that hold all of ``must`` and none of ``without``, within the given sizes, supports and interval widths."""
    ids = lambda xs: F.array(*map(F.lit, xs)) if xs else F.array().cast("array<int>")
    out = sets.where((F.size("items") >= min_size) & (F.col("support") >= min_support))
    out = out.where(contains_all(F.col("items"), ids(must)) & contains_none(F.col("items"), ids(without)))
    for column, most in ((F.size("items"), max_size), (F.col("support"), max_support), (F.col("upper") - F.col("lower") if max_width is not None else None, max_width)):
        if most is not None:
            out = out.where(column <= most)
    return out


def refresh(run: Run, added: Database) -> Run:
    """The representation of the old baskets and new ones with the same dictionary.

    What was derivable may not be any more, so the union is mined again; both parts are merged weighted baskets, which is what makes that cheap.
    """
    both = run.db.baskets.unionByName(added.baskets).groupBy("items").agg(F.sum("weight").alias("weight"))
    counts = run.db.items.unionByName(added.items).groupBy("item_id", "item").agg(F.sum("support").alias("support"))
    return mine(Database(both, counts, run.db.n_baskets + added.n_baskets, counts.count()), run.min_support, max_depth=run.max_depth)
