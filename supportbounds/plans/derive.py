"""All frequent itemsets, and answers about any itemset, from the representation alone: the baskets are not read again.

Sizes go upward. A candidate has all its immediate subsets frequent. If one of them has an exact base X (a rule that gave its support:
it was derived, or kept with a support equal to a bound), then X plus the new item is an exact base for the candidate,
of the same depth: one rule is evaluated. Otherwise the candidate was one of the miner's own: its bounds are computed at the
miner's depth, and equal bounds are its support; unequal ones mean that it was counted and found infrequent.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supportbounds.operators import rules
from supportbounds.operators.itemsets import contains_all, generate, immediate_subsets
from supportbounds.plans.levelwise import Run, _union, with_empty_set
from supportbounds.plans.workspace import keep


@dataclass
class Derivation:
    """``sets``: items, k, support, is_derived, base (the exact base, null if none)."""

    sets: DataFrame
    inherited: dict[int, int] = field(default_factory=dict)
    evaluated: dict[int, int] = field(default_factory=dict)


def all_frequent(run: Run, inherit: bool = True, within: DataFrame | None = None, max_size: int | None = None) -> Derivation:
    """Every frequent itemset with its exact support.

    ``inherit=False`` evaluates all rules for every candidate (full depth only). ``within`` (items) restricts the result to the
    subsets of given itemsets. ``max_size`` ends early: the longest frequent set may be much longer than the longest kept one.
    """
    if not inherit and run.max_depth is not None:
        raise ValueError("with limited depth a base must be inherited")
    exact = F.when(F.col("support") == F.col("lower"), F.col("lower_base")).when(F.col("support") == F.col("upper"), F.col("upper_base"))
    kept = run.sets.select("items", "k", "support", F.lit(False).alias("is_derived"), exact.alias("base"))
    inside = lambda sets: sets if within is None else sets.join(_within(sets.select(F.col("items").alias("part")), within).select(F.col("part").alias("items")).distinct(), "items", "left_semi")
    kept = inside(kept)
    out = Derivation(None)
    levels = [keep(kept.where("k = 1"), "frequent-1")]
    k = 1
    while levels[-1].count() > 1 and (max_size is None or k < max_size):
        gen = inside(generate(levels[-1].select("items"), k))
        k += 1
        open_ones = keep(gen.join(kept.where(F.col("k") == k).select("items"), "items", "left_anti"), "open")
        known = with_empty_set(_union(levels).select("items", "support"), run.db.n_baskets)
        subsets = open_ones.select("items", F.explode(immediate_subsets(F.col("items"))).alias("x")).select("items", F.col("x.dropped").alias("added"), F.col("x.rest").alias("rest"))
        based = subsets.join(levels[-1].where("base IS NOT NULL").select(F.col("items").alias("rest"), "base"), "rest")
        wider = F.array_sort(F.concat("base", F.array("added")))
        best = based.groupBy("items").agg(F.min(F.struct((F.size("items") - F.size(wider)).alias("depth"), wider.alias("base"))).alias("b"))
        inherited = keep(best.select("items", F.col("b.base").alias("base")) if inherit else best.where("false").select("items", F.col("b.base").alias("base")), "inherited")
        by_rule = rules.single(inherited, known).select("items", F.col("sigma").alias("support"), "base")
        rest = keep(open_ones.join(inherited, "items", "left_anti"), "rest")
        n_rest = rest.count()
        derived = by_rule
        if n_rest:
            bounded = rules.bounds(rest, known, k, run.max_depth)
            derived = derived.unionByName(bounded.where("lower = upper").select("items", F.col("lower").alias("support"), F.col("lower_base").alias("base")))
        out.inherited[k], out.evaluated[k] = inherited.count(), n_rest
        derived = derived.where(F.col("support") >= run.min_support).select("items", F.lit(k).alias("k"), "support", F.lit(True).alias("is_derived"), "base")
        levels.append(keep(kept.where(F.col("k") == k).unionByName(derived), f"frequent-{k}"))
    out.sets = _union(levels)
    return out


def derivable(run: Run, **options) -> DataFrame:
    """Only the frequent itemsets that the representation does not list."""
    return all_frequent(run, **options).sets.where("is_derived")


#: Itemsets whose supports may be asked for on the way to an answer.
MOST_ASKED = 5_000_000


def _within(sets: DataFrame, over: DataFrame) -> DataFrame:
    """(items, part, ...) for the rows of ``sets`` (part, ...) whose part lies inside an itemset of ``over``; they meet on the part's last item."""
    left = over.select("items", F.explode("items").alias("__last"))
    right = sets.withColumn("__last", F.element_at("part", -1))
    return left.join(right, "__last").where(contains_all(F.col("items"), F.col("part"))).drop("__last")


def _sources(run: Run, wanted: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(part, base): minimal itemsets inside the wanted ones with an exact base; (part): minimal infrequent ones that are no single items."""
    kept = run.sets.withColumn("part", F.col("items")).drop("items")
    held = keep(_within(kept.select("part", "k"), wanted).select("part", "k").distinct(), "held").join(kept.drop("k"), "part")
    exact = F.when(F.col("support") == F.col("lower"), F.col("lower_base")).when(F.col("support") == F.col("upper"), F.col("upper_base"))
    bases, out = [held.select("part", exact.alias("base")).where("base IS NOT NULL")], []
    known = run.supports()
    for k in [r.k for r in held.where("extendable").select("k").distinct().orderBy("k").collect()]:  # as many rows as sizes
        gen = generate(held.where(F.col("extendable") & (F.col("k") == k)).select(F.col("part").alias("items")), k)
        gen = keep(gen.join(run.sets.select("items"), "items", "left_anti"), "minimal")
        found = rules.bounds(gen, known, k + 1, run.max_depth)
        tight = (F.col("lower") == F.col("upper")) & (F.col("lower") >= run.min_support)
        found = keep(found.select(F.col("items").alias("part"), F.when(tight, F.col("lower_base")).alias("base")), "minimal-bounds")
        bases.append(found.where("base IS NOT NULL"))
        out.append(found.where("base IS NULL").select("part"))
    none = run.sets.sparkSession.createDataFrame([], "part array<int>")
    return keep(_union(bases), "exact-sources"), keep(_union([none, *out]), "infrequent-sources")


def lookup(run: Run, wanted: DataFrame) -> DataFrame:
    """(items, status, support) for each of the given itemsets, of any size: ``frequent`` with its support, or ``infrequent``.

    An itemset that is not kept and holds no minimal infrequent one has an exact rule, inherited from a part of it: 2^depth - 1 smaller itemsets are
    asked for, and so on down to kept ones. The subsets of the wanted itemsets are never listed. Should more than MOST_ASKED
    itemsets be needed, an error says so.
    """
    spark = run.sets.sparkSession
    asked = keep(wanted.select(F.array_sort(F.array_distinct("items")).alias("items")).distinct(), "asked")
    bases, out = _sources(run, asked)
    known = keep(run.supports(), "known")
    singles = run.sets.where("k = 1").select(F.element_at("items", 1).alias("i"))
    rounds, new, total = [], asked.join(known.select("items"), "items", "left_anti"), 0
    every = asked
    while True:
        new = keep(new, "new")
        n = new.count()
        total += n
        if total > MOST_ASKED:
            raise ValueError(f"more than {MOST_ASKED} itemsets are needed to answer")
        if not n:
            break
        strange = new.select("items", F.explode("items").alias("i")).join(singles, "i", "left_anti").select("items")
        hopeless = keep(strange.unionByName(_within(out, new).select("items")).distinct(), "hopeless")
        based = _within(bases, new.join(hopeless, "items", "left_anti"))
        depth = F.size("part") - F.size("base")
        best = based.groupBy("items").agg(F.min(F.struct(depth.alias("d"), F.size("part").alias("n"), "part", "base")).alias("b"))
        wider = F.array_sort(F.array_union("b.base", F.array_except("items", "b.part")))
        rules_now = keep(best.select("items", wider.alias("base")), "rules")
        rounds.append(rules_now)
        terms = rules.terms(rules_now).select(F.col("term").alias("items")).distinct()
        every = keep(every.unionByName(new).distinct(), "every")
        new = terms.join(known.select("items"), "items", "left_anti").join(every, "items", "left_anti")
    if rounds:
        whole = keep(_union(rounds).distinct(), "all-rules")
        for size in sorted(r.n for r in whole.select(F.size("items").alias("n")).distinct().collect()):  # as many rows as sizes
            found = rules.single(whole.where(F.size("items") == size), known, complete=True).where(F.col("sigma") >= run.min_support)
            known = keep(known.unionByName(found.select("items", F.col("sigma").alias("support"))), "known")
    named = wanted.select("items", F.array_sort(F.array_distinct("items")).alias("sorted"))
    out = named.join(known.withColumnRenamed("items", "sorted"), "sorted", "left")
    return out.select("items", F.when(F.col("support").isNull(), "infrequent").otherwise("frequent").alias("status"), "support")
