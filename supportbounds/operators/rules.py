"""Deduction rules: bounds on the support of an itemset J from the supports of its subsets.

For every base I inside J, inclusion-exclusion over the sets between I and J gives one bound:

    sigma(I, J) = sum over X, I <= X < J, of (-1)^(|J - X| + 1) * support(X)

an upper bound if the depth |J - I| is odd, a lower bound if it is even; it misses the support by
exactly the number of baskets whose part within J is I. The rule of J itself (depth 0) says support >= 0.

Four kernels give equal bounds. ``lattice`` puts the supports of the subsets into an array indexed
by position mask and turns it into all sums at once by one subtraction pass per item, in expressions; ``arrow``
does the same in vectorised batches; ``relational`` joins a broadcast table of rule terms and sums signed supports; ``by_rule`` evaluates each
rule up to the depth by itself, so that its work is the number of those rules' terms, whatever the size of the itemset. By default it is
``by_rule`` where that is less work than 2^n entries, else ``lattice``.
Among bases with the same bound the one of least depth, then least mask, is reported.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from supportbounds.operators.itemsets import k_subsets, pick

MAX_SIZE = 16
KERNELS = ("lattice", "arrow", "relational", "by_rule")


def template_rows(n: int, max_depth: int | None = None) -> Iterator[tuple[int, int, int, int, int]]:
    """(n, base_mask, term_mask, sign, depth) of every term of every rule of an n-set, up to the given depth."""
    full = (1 << n) - 1
    for depth in range(1, (n if max_depth is None else min(n, max_depth)) + 1):
        for places in combinations(range(n), depth):
            free = sum(1 << i for i in places)
            base, extra = full & ~free, (free - 1) & free  # all proper subsets of what may be added
            while True:
                yield n, base, base | extra, -1 if (n - (base | extra).bit_count()) % 2 == 0 else 1, depth
                if extra == 0:
                    break
                extra = (extra - 1) & free


def template(spark: SparkSession, n: int, max_depth: int | None = None) -> DataFrame:
    _check(n)
    return spark.createDataFrame(list(template_rows(n, max_depth)), "n int, base_mask long, term_mask long, sign int, depth int")


def _check(n: int) -> None:
    if n > MAX_SIZE:
        raise ValueError(f"an itemset of {n} items has 2^{n} rules; give max_depth (and no kernel) or at most {MAX_SIZE} items")


def _kernel(n: int, depth: int) -> str:
    return "by_rule" if n > MAX_SIZE and depth < n or n > 10 and rule_counts(n, depth)[1] < 1 << n else "lattice"


def _with_subsets(sets: DataFrame, supports: DataFrame, n: int, max_depth: int | None) -> DataFrame:
    """(items, mask, s): the supports of the proper subsets that rules up to the depth need."""
    least = 0 if max_depth is None else max(0, n - max_depth)
    masks = F.array(*[F.lit(m) for m in range((1 << n) - 1) if m.bit_count() >= least]) if n <= 6 else F.filter(F.sequence(F.lit(0), F.lit((1 << n) - 2)), lambda m: F.bit_count(m) >= least)
    rows = sets.select("items", F.explode(masks).alias("mask"))
    parts = rows.select("items", "mask", pick(F.col("items"), F.col("mask")).alias("part"))
    return parts.join(supports.select(F.col("items").alias("part"), F.col("support").alias("s")), "part").select("items", "mask", "s")


def sigmas(sets: DataFrame, supports: DataFrame, n: int, max_depth: int | None = None) -> DataFrame:
    """(items, sigma): for each n-set an array over all position masks; entries beyond the depth are null.

    ``supports`` (items, support) must hold the empty set and every proper subset the rules need.
    """
    _check(n)
    depth = n if max_depth is None else min(max_depth, n)
    held = _with_subsets(sets, supports, n, depth).groupBy("items").agg(F.map_from_entries(F.collect_list(F.struct("mask", "s"))).alias("by_mask"))
    start = F.transform(F.sequence(F.lit(0), F.lit((1 << n) - 1)), lambda m: F.coalesce(F.element_at("by_mask", m), F.lit(0).cast("long")))
    sums = F.aggregate(F.sequence(F.lit(0), F.lit(n - 1)), start, _subtract_with)
    sign = lambda g, m: F.when(n - F.bit_count(m) > depth, None).when((n - F.bit_count(m)) % 2 == 0, -g).otherwise(g)
    return held.select("items", F.transform(sums, sign).alias("sigma"))


def _subtract_with(g: Column, bit: Column) -> Column:
    """One pass: from each entry without the bit the entry with it is taken away."""
    return F.transform(g, lambda v, m: F.when(F.getbit(m, bit) == 0, v - F.get(g, m + F.call_function("shiftleft", F.lit(1), bit))).otherwise(v))


def bounds(sets: DataFrame, supports: DataFrame, n: int, max_depth: int | None = None, kernel: str = "auto") -> DataFrame:
    """(items, lower, upper, lower_base, upper_base) for each n-set."""
    depth = n if max_depth is None else min(max_depth, n)
    if depth < 1:
        raise ValueError("rules need a depth of 1 or more")
    if kernel == "auto":
        kernel = _kernel(n, depth)
    if kernel == "by_rule":
        return _by_rule(sets, supports, depth)
    _check(n)
    if kernel == "relational":
        return _relational(sets, supports, n, depth)
    if kernel == "arrow":
        return _arrow(sets, supports, n, depth)
    df = sigmas(sets, supports, n, depth)
    ranked = F.transform("sigma", lambda s, m: F.struct(s.alias("s"), (n - F.bit_count(m)).alias("d"), m.alias("m")))
    usable = F.filter(ranked, lambda x: x["s"].isNotNull())
    low = F.array_max(F.transform(F.filter(usable, lambda x: x["d"] % 2 == 0), lambda x: F.struct(x["s"].alias("s"), (-x["d"]).alias("d"), (-x["m"]).alias("m"))))
    high = F.array_min(F.filter(usable, lambda x: x["d"] % 2 == 1))
    df = df.withColumns({"low": low, "high": high})
    items = F.col("items")
    return df.select("items", F.col("low.s").alias("lower"), F.col("high.s").alias("upper"), pick(items, -F.col("low.m")).alias("lower_base"), pick(items, F.col("high.m")).alias("upper_base"))


def _relational(sets: DataFrame, supports: DataFrame, n: int, depth: int) -> DataFrame:
    terms = F.broadcast(template(sets.sparkSession, n, depth).select("base_mask", F.col("term_mask").alias("mask"), "sign", "depth"))
    rows = _with_subsets(sets, supports, n, depth).join(terms, "mask")
    sums = rows.groupBy("items", "base_mask").agg(F.sum(F.col("sign") * F.col("s")).alias("s"), F.first("depth").alias("d"))
    even = F.col("d") % 2 == 0
    best = sums.groupBy("items").agg(
        F.max(F.when(even, F.struct("s", (-F.col("d")).alias("d"), (-F.col("base_mask")).alias("m")))).alias("low"),
        F.min(F.when(~even, F.struct("s", "d", F.col("base_mask").alias("m")))).alias("high"),
    )
    own = F.col("low").isNull() | (F.col("low.s") <= 0)  # the rule of the set itself: depth 0, at least 0
    items = F.col("items")
    return best.select(
        "items", F.when(own, 0).otherwise(F.col("low.s")).cast("long").alias("lower"), F.col("high.s").alias("upper"),
        F.when(own, items).otherwise(pick(items, -F.col("low.m"))).alias("lower_base"), pick(items, F.col("high.m")).alias("upper_base"),
    )


def evaluate(sets: DataFrame, supports: DataFrame, depth: int) -> DataFrame:
    """(items, base, depth, sigma) of every rule of depth 1 to ``depth``; C(n, d) rules of 2^d - 1 terms for each d."""
    items = F.col("items")
    bases = F.concat(*[F.transform(k_subsets(items, d), lambda dropped: F.array_except(items, dropped)) for d in range(1, depth + 1)])
    found = single(sets.select("items", F.explode(bases).alias("base")), supports)
    return found.select("items", "base", (F.size("items") - F.size("base")).alias("depth"), "sigma")


def _by_rule(sets: DataFrame, supports: DataFrame, depth: int) -> DataFrame:
    even, place = F.col("depth") % 2 == 0, F.reverse("base")  # from the last item on: the order of the position masks
    best = evaluate(sets, supports, depth).groupBy("items").agg(
        F.min(F.when(even, F.struct((-F.col("sigma")).alias("s"), "depth", place.alias("base")))).alias("low"),
        F.min(F.when(~even, F.struct(F.col("sigma").alias("s"), "depth", place.alias("base")))).alias("high"),
    )
    own = F.col("low").isNull() | (F.col("low.s") >= 0)  # the rule of the set itself: depth 0, at least 0
    return best.select(
        "items", F.when(own, 0).otherwise(-F.col("low.s")).cast("long").alias("lower"), F.col("high.s").alias("upper"),
        F.when(own, F.col("items")).otherwise(F.reverse("low.base")).alias("lower_base"), F.reverse("high.base").alias("upper_base"),
    )


def _arrow(sets: DataFrame, supports: DataFrame, n: int, depth: int) -> DataFrame:
    held = _with_subsets(sets, supports, n, depth).groupBy("items").agg(F.collect_list("mask").alias("masks"), F.collect_list("s").alias("s"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        size = 1 << n
        masks = np.arange(size)
        d = n - np.bitwise_count(masks).astype(np.int64)
        order = np.lexsort((masks, d))  # the first of equal bounds is the one of least depth, then least mask
        low, high = order[(d[order] % 2 == 0) & (d[order] <= depth)], order[(d[order] % 2 == 1) & (d[order] <= depth)]
        for batch in batches:
            rows = batch.num_rows
            g = np.zeros((rows, size), dtype=np.int64)
            at = np.repeat(np.arange(rows), np.diff(batch.column("masks").offsets.to_numpy()))
            g[at, batch.column("masks").flatten().to_numpy()] = batch.column("s").flatten().to_numpy()
            for bit in range(n):
                without = masks[masks >> bit & 1 == 0]
                g[:, without] -= g[:, without | 1 << bit]
            sigma = np.where(d % 2 == 0, -g, g)
            lo, hi = low[np.argmax(sigma[:, low], axis=1)], high[np.argmin(sigma[:, high], axis=1)]
            r = np.arange(rows)
            yield pa.RecordBatch.from_arrays([batch.column("items"), pa.array(sigma[r, lo]), pa.array(sigma[r, hi]), pa.array(lo), pa.array(hi)], names=["items", "lower", "upper", "lo", "hi"])

    found = held.mapInArrow(run, "items array<int>, lower long, upper long, lo long, hi long")
    return found.select("items", "lower", "upper", pick(F.col("items"), F.col("lo")).alias("lower_base"), pick(F.col("items"), F.col("hi")).alias("upper_base"))


def explain(sets: DataFrame, supports: DataFrame, n: int, max_depth: int | None = None) -> DataFrame:
    """Every rule of each n-set: (items, base, depth, side, sigma)."""
    if n > MAX_SIZE and max_depth is not None and max_depth < n:
        whole = sets.select("items", F.col("items").alias("base"), F.lit(0).alias("depth"), F.lit(0).cast("long").alias("sigma"))
        found = evaluate(sets, supports, max_depth).unionByName(whole)
        return found.select("items", "base", "depth", F.when(F.col("depth") % 2 == 0, "lower").otherwise("upper").alias("side"), "sigma")
    df = sigmas(sets, supports, n, max_depth).select("items", F.posexplode("sigma").alias("mask", "sigma")).where("sigma IS NOT NULL")
    depth = F.lit(n) - F.bit_count("mask")
    return df.select("items", pick(F.col("items"), F.col("mask")).alias("base"), depth.alias("depth"), F.when(depth % 2 == 0, "lower").otherwise("upper").alias("side"), "sigma")


def terms(pairs: DataFrame) -> DataFrame:
    """(items, base, term, sign): the itemsets whose supports the rule of each row (items, base) adds up."""
    free = F.array_except("items", "base")
    rows = pairs.select("items", "base", free.alias("free"), F.explode(F.sequence(F.lit(0), F.call_function("shiftleft", F.lit(1), F.size(free)) - 2)).alias("mask"))
    sign = F.when((F.size("free") - F.bit_count("mask")) % 2 == 1, 1).otherwise(-1)
    return rows.select("items", "base", F.array_sort(F.concat("base", pick(F.col("free"), F.col("mask")))).alias("term"), sign.alias("sign"))


def single(pairs: DataFrame, supports: DataFrame, complete: bool = False) -> DataFrame:
    """(items, base, sigma) of one rule for each row (items, base): 2^depth - 1 terms instead of all rules.

    ``complete``: rows of which a term has no support in ``supports`` are left out.
    """
    joined = terms(pairs).join(supports.select(F.col("items").alias("term"), F.col("support").alias("s")), "term", "left" if complete else "inner")
    sums = joined.groupBy("items", "base").agg(F.sum(F.col("sign") * F.col("s")).alias("sigma"), F.bool_and(F.col("s").isNotNull()).alias("all"))
    return sums.where("all").select("items", "base", "sigma")


def inconsistent(bounded: DataFrame) -> DataFrame:
    """Itemsets whose given subset supports no database can have."""
    return bounded.where(F.col("lower") > F.col("upper"))


def rule_counts(n: int, max_depth: int | None = None) -> tuple[int, int]:
    """(rules, terms) evaluated for one n-set: bases of depth 1 to the limit, and the supports they add up."""
    depths = range(1, (n if max_depth is None else min(n, max_depth)) + 1)
    return sum(comb(n, d) for d in depths), sum(comb(n, d) * ((1 << d) - 1) for d in depths)
