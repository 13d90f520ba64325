"""Baskets (transactions): encoders from any table, the item dictionary, and the encoded database.

A basket view has the columns ``basket_id`` and ``items`` (array of strings). Encoding gives items dense ids, 0 for
the most frequent, and merges equal baskets into one row with a weight. Empty baskets stay (as one weighted row).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from supportbounds.plans.workspace import dense_ids, keep, small

#: Up to so many items a basket is also held as the bits of one integer.
MASK_ITEMS = 62
WORD_BREAK = r"[^\p{L}\p{N}]+"


def from_groups(df: DataFrame, key: Column | str, item: Column | str) -> DataFrame:
    """One basket for each value of ``key`` that has an item."""
    key, item = (F.col(c) if isinstance(c, str) else c for c in (key, item))
    pairs = df.select(key.alias("basket_id"), item.cast("string").alias("item")).where("item IS NOT NULL").distinct()
    return pairs.groupBy("basket_id").agg(F.collect_list("item").alias("items"))


def from_columns(df: DataFrame, key: Column | str, columns: dict[str, Column]) -> DataFrame:
    """One basket per row, with an item ``name=value`` for each column that is not null."""
    key = F.col(key) if isinstance(key, str) else key
    items = [F.when(value.isNotNull(), F.concat(F.lit(f"{name}="), value.cast("string"))) for name, value in columns.items()]
    return df.select(key.alias("basket_id"), F.array_compact(F.array(*items)).alias("items"))


def from_text(df: DataFrame, key: str, text: str, pattern: str = WORD_BREAK) -> DataFrame:
    """One basket per row: its distinct lower-cased words."""
    words = F.array_distinct(F.filter(F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), pattern), lambda w: w != ""))
    return df.select(F.col(key).alias("basket_id"), words.alias("items"))


def from_lines(df: DataFrame, key: str, text: str) -> DataFrame:
    lines = F.array_distinct(F.filter(F.split(F.coalesce(F.col(text), F.lit("")), "\n"), lambda x: x != ""))
    return df.select(F.col(key).alias("basket_id"), lines.alias("items"))


def from_vector_signs(df: DataFrame, key: str, vector: str) -> DataFrame:
    """One item for each positive component."""
    signs = F.filter(F.transform(vector, lambda v, i: F.when(v > 0, F.concat(F.lit("d"), i.cast("string")))), lambda x: x.isNotNull())
    return df.select(F.col(key).alias("basket_id"), signs.alias("items"))


def with_empty(baskets: DataFrame, universe: DataFrame, key: str) -> DataFrame:
    """Adds an empty basket for each key of ``universe`` that has none."""
    ids = universe.select(F.col(key).alias("basket_id")).distinct()
    return ids.join(baskets, "basket_id", "left").withColumn("items", F.coalesce("items", F.array().cast("array<string>")))


def project(baskets: DataFrame, items: list) -> DataFrame:
    """Every basket cut down to ``items``; none is dropped."""
    kept = F.array(*map(F.lit, items)) if items else F.array().cast(baskets.schema["items"].dataType)
    return baskets.withColumn("items", F.array_intersect("items", kept))


@dataclass
class Database:
    """Encoded baskets ``(items array<int>, weight)``, the dictionary ``(item_id, item, support)`` and the number of baskets."""

    baskets: DataFrame
    items: DataFrame
    n_baskets: int
    n_items: int

    def named(self, df: DataFrame, column: str = "items") -> DataFrame:
        """``df`` with item ids written as one string of names.

        The dictionary of the *result's* items is joined; a small one is broadcast.
        """
        if self.n_items <= 4096:
            names = F.array(*[F.lit(r.item) for r in self.items.orderBy("item_id").collect()] or [F.lit("")])
            return df.withColumn(column, F.array_join(F.transform(column, lambda i: F.get(names, i)), " "))
        keyed = df.withColumn("__row", F.monotonically_increasing_id())
        pairs = keyed.select("__row", F.posexplode_outer(column).alias("at", "item_id")).join(small(self.items.select("item_id", "item")), "item_id", "left")
        text = pairs.groupBy("__row").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("at", "item"))), lambda x: x["item"]), " ").alias("__names"))
        return keyed.join(text, "__row").withColumn(column, F.col("__names")).drop("__row", "__names")

    def masks(self) -> DataFrame:
        """(mask, weight): baskets as bits; only for up to MASK_ITEMS items."""
        if self.n_items > MASK_ITEMS:
            raise ValueError(f"{self.n_items} items don't fit into one integer")
        bits = F.aggregate("items", F.lit(0).cast("long"), lambda a, i: a.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), i)))
        return self.baskets.select(bits.alias("mask"), "weight")


def numbered(df: DataFrame, name: str) -> DataFrame:
    """``df`` with a number for each row, given before arrays are exploded (beside a generator each of its rows would get its own)."""
    return df.withColumn(name, F.monotonically_increasing_id())


def reduced(db: Database, items: DataFrame, least: int) -> Database:
    """``db`` with baskets cut down to the given items (item_id) and merged anew; those with fewer than ``least`` of them go.

    Supports of itemsets of ``least`` or more of these items stay what they are, and so does the number of baskets.
    """
    rows = numbered(db.baskets.where(F.size("items") >= least), "b").select("b", "weight", F.explode("items").alias("item_id"))
    cut = rows.join(small(items.select("item_id")), "item_id", "left_semi").groupBy("b", "weight").agg(F.array_sort(F.collect_list("item_id")).alias("items"))
    merged = cut.where(F.size("items") >= least).groupBy("items").agg(F.sum("weight").alias("weight"))
    return Database(keep(merged, "reduced-baskets"), db.items, db.n_baskets, db.n_items)


def item_supports(baskets: DataFrame) -> DataFrame:
    """(item, support) over all baskets; an item counts once in a basket, nulls don't count."""
    items = F.array_distinct(F.array_compact("items"))
    return baskets.select(F.explode(items).alias("item")).groupBy("item").agg(F.count("*").alias("support"))


def encode(baskets: DataFrame, min_support: int = 1, top: int | None = None, only: list[str] | None = None) -> Database:
    """Dictionary and encoded baskets.

    Items below ``min_support`` are left out (no frequent set holds them), as are those outside ``only`` or
    the ``top`` most frequent. Baskets are read twice: once for the counts, once to be encoded.
    """
    counts = item_supports(baskets).where(F.col("support") >= min_support)
    if only is not None:
        counts = counts.where(F.col("item").isin(only))
    order = [F.desc("support"), F.asc("item")]
    if top is not None:
        counts = counts.orderBy(*order).limit(top)
    items = keep(dense_ids(counts, order, "item_id").select(F.col("item_id").cast("int").alias("item_id"), "item", "support"), "items")
    n_items = items.count()
    if n_items <= MASK_ITEMS:  # a handful of literals: no shuffle of the baskets' items
        names = [r.item for r in items.orderBy("item_id").collect()]
        found = F.array_compact(F.array(*[F.when(F.array_contains("items", n), F.lit(i)) for i, n in enumerate(names)])) if names else F.array().cast("array<int>")
        encoded = baskets.select(found.alias("items"))
    else:
        rows = numbered(baskets, "row").select("row", F.explode_outer(F.array_distinct(F.array_compact("items"))).alias("item"))
        ids = rows.join(small(items.select("item", "item_id")), "item", "left")
        encoded = ids.groupBy("row").agg(F.array_sort(F.collect_list("item_id")).alias("items"))  # nulls are not collected
    merged = keep(encoded.groupBy("items").agg(F.count("*").alias("weight")), "baskets")
    n_baskets = merged.agg(F.coalesce(F.sum("weight"), F.lit(0))).first()[0]
    return Database(merged, items, n_baskets, n_items)


def resolve_support(threshold: float | int, n_baskets: int, strict: bool = False) -> int:
    """A threshold as a number of baskets: fractions below one are shares; ``strict`` asks for more than the threshold."""
    from math import ceil, floor

    if isinstance(threshold, float) and threshold < 1:
        exact = threshold * n_baskets
        return max(1, floor(exact) + 1 if strict else ceil(exact - 1e-9))
    return max(1, int(threshold) + strict)
