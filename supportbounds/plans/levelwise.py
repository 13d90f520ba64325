"""Level-wise mining: the itemsets whose support cannot be deduced, and the baselines it is compared with.

One loop serves all of them. A level is: candidates from the extendable sets, bounds from the supports of the
levels below, one counting pass for what the bounds leave open, and the test which sets are extended. Each level is
written to the shared folder; only counts of rows come to the driver.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from math import comb

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supportbounds.operators import rules, support
from supportbounds.operators.baskets import Database, reduced
from supportbounds.operators.itemsets import empty, generate, immediate_subsets
from supportbounds.plans.workspace import keep

#: Up to so many extendable items their pairs are listed as candidates; beyond, pairs are counted from the baskets.
LISTED_PAIRS = 3_000

SET_SCHEMA = "items array<int>, k int, support long, lower long, upper long, lower_base array<int>, upper_base array<int>, extendable boolean"
CANDIDATE_SCHEMA = "items array<int>, k int, lower long, upper long"


@dataclass
class Level:
    """What happened on one level."""

    k: int
    generated: int = 0
    dropped: int = 0
    pruned_upper: int = 0
    counted: int = 0
    infrequent: int = 0
    not_extended: int = 0


@dataclass
class Run:
    """A mined representation: the kept sets, and the measures of the run."""

    db: Database
    min_support: int
    max_depth: int | None
    sets: DataFrame
    candidates: DataFrame  # all candidates with their interval, those found derivable too
    levels: list[Level] = field(default_factory=list)

    @property
    def scans(self) -> int:
        """Passes over the baskets (the first one counts the items)."""
        return sum(level.counted > 0 for level in self.levels)

    def supports(self) -> DataFrame:
        """(items, support) of the kept sets and the empty set."""
        return with_empty_set(self.sets.select("items", "support"), self.db.n_baskets)


def with_empty_set(supports: DataFrame, n_baskets: int) -> DataFrame:
    row = supports.sparkSession.range(1).select(empty().alias("items"), F.lit(n_baskets).cast("long").alias("support"))
    return supports.unionByName(row)


def max_level(n_baskets: int, min_support: int, max_depth: int | None) -> int:
    """A size that no kept set exceeds.

    An extendable set of size n has a basket of its own behind each rule up to the depth, and ``min_support``
    more: min_support + sum of C(n, d) for d = 1..depth is at most the number of baskets. Kept sets are one item longer at most.
    """
    n = 0
    while min_support + sum(comb(n + 1, d) for d in range(1, min(n + 1, max_depth or n + 1) + 1)) <= n_baskets:
        n += 1
    return n + 1


def mine(
    db: Database, min_support: int, max_depth: int | None = None, equality_prune: bool = True, prune_upper: bool = False, max_size: int | None = None,
    counting: str = "auto", kernel: str = "auto", bounding: bool = True, listed_pairs: int = LISTED_PAIRS,
) -> Run:
    """The frequent itemsets whose support rules up to ``max_depth`` cannot deduce (all depths by default).

    ``equality_prune``: sets whose support equals a bound are kept, not extended. ``prune_upper``: candidates that
    cannot be frequent are not counted. ``bounding=False`` leaves the rules out: all frequent itemsets, by monotonicity alone.
    With more than ``listed_pairs`` extendable items, pairs are counted from the baskets; those that no basket holds are in the numbers of the level, not in the table
    of candidates. Before each level, baskets are cut down to the items that can still be extended where that leaves out a good part of them.
    """
    spark = db.baskets.sparkSession
    n = db.n_baskets
    singles = db.items.select(F.array("item_id").alias("items"), "support").select(
        "items", F.lit(1).alias("k"), "support", F.lit(0).cast("long").alias("lower"), F.lit(n).cast("long").alias("upper"), F.col("items").alias("lower_base"), empty().alias("upper_base")
    )
    run = Run(db, min_support, max_depth, None, None)
    kept: list[DataFrame] = []
    tried: list[DataFrame] = [singles.select("items", "k", "lower", "upper")]
    level = Level(1, generated=db.n_items, counted=db.n_items)
    counted, k, small_db, n_items = singles, 1, db, db.n_items
    limit = max_size or (max_level(n, min_support, max_depth) if bounding and equality_prune else db.n_items)
    while True:
        off_bounds = (F.col("support") != F.col("lower")) & (F.col("support") != F.col("upper")) if bounding and equality_prune else F.lit(True)
        sets = keep(counted.where(F.col("support") >= min_support).withColumn("extendable", off_bounds), f"kept-{k}")
        kept.append(sets)
        sizes = sets.agg(F.count("*"), F.count_if("extendable")).first()
        level.infrequent, level.not_extended = level.counted - sizes[0], sizes[0] - sizes[1]
        run.levels.append(level)
        if sizes[1] < 2 or k >= limit:
            break
        used = keep(sets.where("extendable").select(F.explode("items").alias("item_id")).distinct(), "used-items")
        n_used = used.count()
        if n_used < 0.8 * n_items:
            small_db, n_items = reduced(small_db, used, k + 1), n_used
        from_baskets = k == 1 and sizes[1] > listed_pairs
        if from_baskets:
            paired = keep(support.pairs(small_db, used), "pairs")
            gen = paired.select("items")
        else:
            gen = generate(sets.where("extendable").select("items"), k)
        k += 1
        if bounding:
            below = _union(kept[-max_depth:] if max_depth else kept).select("items", "support")
            known = with_empty_set(below, n) if not max_depth or max_depth >= k else below
            bounded = rules.bounds(gen, known, k, max_depth, kernel)
        else:
            none = F.lit(None).cast("array<int>")
            bounded = gen.select("items", F.lit(0).cast("long").alias("lower"), F.lit(n).cast("long").alias("upper"), none.alias("lower_base"), none.alias("upper_base"))
        bounded = keep(bounded.withColumn("k", F.lit(k)), f"bounded-{k}")
        tried.append(bounded.select("items", "k", "lower", "upper"))
        tight = F.col("lower") == F.col("upper")
        hopeless = ~tight & (F.col("upper") < min_support) if prune_upper else F.lit(False)
        total, derivable, out = bounded.agg(F.count("*"), F.count_if(tight), F.count_if(hopeless)).first()
        unseen = comb(sizes[1], 2) - total if from_baskets else 0  # pairs of no basket: support 0, which no rule can tell
        level = Level(k, total + unseen, derivable, out, total + unseen - derivable - out)
        if not level.counted:
            if total:
                run.levels.append(level)
            break
        open_ones = bounded.where(~tight & ~hopeless)
        found = paired if from_baskets else support.count(small_db, open_ones, k, counting, level.counted)
        counted = open_ones.join(found, "items").select("items", "k", "support", "lower", "upper", "lower_base", "upper_base")
    run.sets = _union(kept) if kept else spark.createDataFrame([], SET_SCHEMA)
    run.candidates = _union(tried)
    return run


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


def mine_nonderivable(db: Database, min_support: int, **options) -> Run:
    return mine(db, min_support, **options)


def mine_all_levelwise(db: Database, min_support: int, **options) -> Run:
    """All frequent itemsets by monotonicity alone (the baseline; depth 0)."""
    return mine(db, min_support, bounding=False, equality_prune=False, **options)


def mine_all_fpgrowth(db: Database, min_support: int) -> DataFrame:
    """All frequent itemsets (items, support) by pattern growth.

    The library takes a share of the rows; half a basket less than the threshold guards against rounding. Merged baskets are written out again.
    """
    from pyspark.ml.fpm import FPGrowth

    held = db.baskets.where(F.size("items") > 0)
    # written out in blocks: a weight of any size is no long array
    blocks = held.select("items", "weight", F.explode(F.sequence(F.lit(0).cast("long"), F.expr("(weight - 1) div 4096"))).alias("block"))
    rows = blocks.select("items", F.explode(F.sequence(F.lit(1).cast("long"), F.least(F.lit(4096).cast("long"), F.expr("weight - 4096 * block")))).alias("copy")).select("items")
    n = held.agg(F.coalesce(F.sum("weight"), F.lit(0))).first()[0]
    if not n:
        return db.baskets.sparkSession.createDataFrame([], "items array<int>, support long")
    share = max(0.0, (min_support - 0.5) / n)
    if share >= 1:
        share = 1.0
    model = FPGrowth(itemsCol="items", minSupport=share).fit(rows)
    return model.freqItemsets.where(F.col("freq") >= min_support).select(F.array_sort("items").alias("items"), F.col("freq").alias("support"))


def mine_bruteforce(db: Database) -> DataFrame:
    """(items, support) of every non-empty subset of at most 16 items, from bits alone."""
    if db.n_items > 16:
        raise ValueError("brute force is for 16 items at most")
    bits = F.array(*[F.lit(i) for i in range(db.n_items)])
    sets = db.baskets.sparkSession.range(1, 1 << db.n_items).select(F.col("id").alias("x"))
    held = sets.join(F.broadcast(db.masks()), F.col("mask").bitwiseAND(F.col("x")) == F.col("x"), "left")
    sums = held.groupBy("x").agg(F.coalesce(F.sum("weight"), F.lit(0)).cast("long").alias("support"))
    return sums.select(F.filter(bits, lambda i: F.getbit("x", i) == 1).alias("items"), "support")


def mine_counting_inference(db: Database, min_support: int) -> DataFrame:
    """All frequent itemsets (items, support, inferred): a set with a subset that is not free is inferred, not counted.

    A set is free if no subset with one item less has its support; what is not free has the least support among its subsets.
    """
    n, k = db.n_baskets, 1
    level = db.items.where(F.col("support") >= min_support).select(F.array("item_id").alias("items"), "support", F.lit(False).alias("inferred"), (F.col("support") != n).alias("free"))
    levels = [keep(level, "inference-1")]
    while levels[-1].count() > 1:
        gen = keep(generate(levels[-1].select("items"), k), "inference-candidates")
        k += 1
        subsets = gen.select("items", F.explode(immediate_subsets(F.col("items"))).alias("x")).select("items", F.col("x.rest").alias("rest"))
        below = levels[-1].select(F.col("items").alias("rest"), F.col("support").alias("s"), "free")
        known = keep(subsets.join(below, "rest").groupBy("items").agg(F.min("s").alias("least"), F.bool_and("free").alias("all_free")), "inference-known")
        counted = support.count(db, known.where("all_free"), k)
        both = known.join(counted, "items", "left").withColumn("support", F.when(F.col("all_free"), F.col("support")).otherwise(F.col("least")))
        level = both.where(F.col("support") >= min_support).select("items", "support", (~F.col("all_free")).alias("inferred"), (F.col("support") != F.col("least")).alias("free"))
        levels.append(keep(level, f"inference-{k}"))
    return _union(levels).drop("free")


def mine_maximal_lookahead(db: Database, min_support: int) -> DataFrame:
    """The maximal frequent itemsets (items, support), with long sets found frequent from a lower bound alone.

    For sets that share all but the last item (a head and its tails), the support of head and all tails together is at least
    support(head) - sum over tails of (support(head) - support(head + tail)). Where that reaches the threshold, all
    sets in between are frequent and none of them is counted.
    """
    n, k = db.n_baskets, 1
    spark = db.baskets.sparkSession
    level = keep(db.items.where(F.col("support") >= min_support).select(F.array("item_id").alias("items"), "support"), "lookahead-1")
    heads = with_empty_set(spark.createDataFrame([], "items array<int>, support long"), n)
    levels, long_sets = [level], spark.createDataFrame([], "long_set array<int>")
    while level.count() > 1:
        grouped = level.where("support IS NOT NULL").groupBy(F.slice("items", 1, k - 1).alias("head") if k > 1 else empty().alias("head"))
        tails = grouped.agg(F.array_sort(F.collect_list(F.element_at("items", -1))).alias("tails"), F.sum("support").alias("total"), F.count("*").alias("m"))
        sure = tails.join(heads.select(F.col("items").alias("head"), F.col("support").alias("s")), "head")
        sure = sure.where((F.col("total") - (F.col("m") - 1) * F.col("s") >= min_support) & (F.col("m") > 1)).select(F.array_sort(F.concat("head", "tails")).alias("long_set"))
        long_sets = keep(long_sets.unionByName(sure).distinct(), "long-sets")
        gen = keep(generate(level.select("items"), k), "lookahead-candidates")
        k += 1
        # candidates and long sets meet on their first item
        meets = gen.withColumn("f", F.get("items", F.lit(0))).join(long_sets.select("long_set", F.explode("long_set").alias("f")), "f")
        covered = meets.where(F.size(F.array_except("items", "long_set")) == 0).select("items").distinct()
        open_ones = keep(gen.join(covered, "items", "left_anti"), "lookahead-open")
        counted = support.count(db, open_ones, k).where(F.col("support") >= min_support)
        heads = level.where("support IS NOT NULL")
        level = keep(counted.unionByName(gen.join(covered, "items", "left_semi").withColumn("support", F.lit(None).cast("long"))), f"lookahead-{k}")
        levels.append(level)
    frequent = _union(levels)
    inner = frequent.select(F.explode(immediate_subsets(F.col("items"))).alias("x")).select(F.col("x.rest").alias("items")).distinct()
    tops = keep(frequent.join(inner, "items", "left_anti").select("items", "support", F.size("items").alias("k")), "tops")
    out = [tops.where("support IS NOT NULL").select("items", "support")]
    for size in [r.k for r in tops.where("support IS NULL").select("k").distinct().collect()]:  # a few sizes
        out.append(support.count(db, tops.where((F.col("k") == size) & F.col("support").isNull()), size))
    return _union(out)
