"""One query for each method, variant, baseline, measure and workload, over the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from supportbounds import oracles, workloads
from supportbounds.operators import baskets, fractions, related, rules, support
from supportbounds.operators.baskets import Database
from supportbounds.operators.itemsets import contains_all, contains_any, contains_none, k_subsets, same_items
from supportbounds.plans import checks, derive, measures, represent
from supportbounds.plans.levelwise import (
    Run,
    _union,
    mine_all_fpgrowth,
    mine_all_levelwise,
    mine_bruteforce,
    mine_counting_inference,
    mine_maximal_lookahead,
    mine_nonderivable,
    with_empty_set,
)
from supportbounds.plans.workspace import keep

Query = Callable[[SparkSession, str], DataFrame]
WORD_SUPPORT = 300


def words(spark: SparkSession, d: str, n: int = 10) -> Database:
    return baskets.encode(workloads.doc_word(spark, d), top=n)


def view(spark: SparkSession, d: str, name: str, n: int | None = 10) -> Database:
    return baskets.encode(workloads.VIEWS[name](spark, d), top=n)


def _named(db: Database, df: DataFrame, *columns: str) -> DataFrame:
    return db.named(df.select("items", *columns))


def _four(db: Database) -> tuple[DataFrame, DataFrame]:
    """Supports of all subsets of the four items (or fewer) of ``db``, and the set of all of them."""
    subsets = db.baskets.select("weight", F.explode(F.concat(*[k_subsets(F.col("items"), k) for k in range(db.n_items + 1)])).alias("items"))
    whole = db.baskets.sparkSession.range(1).select(F.array(*map(F.lit, range(db.n_items))).alias("items"))
    return subsets.groupBy("items").agg(F.sum("weight").alias("support")), whole


def rules_of_four(db: Database) -> DataFrame:
    """Every rule of the set of all items of ``db``, as in the worked example."""
    supports, whole = _four(db)
    found = rules.explain(whole, supports, db.n_items)
    return db.named(found.select("base", "depth", "side", "sigma"), "base")


def bounds_of_four(db: Database) -> DataFrame:
    """The bounds of the set of all items of ``db`` by rules up to each depth."""
    supports, whole = _four(db)
    return _union([rules.bounds(whole, supports, db.n_items, k).select(F.lit(k).alias("max_depth"), "lower", "upper") for k in range(1, db.n_items + 1)])


def worked_example_rules(spark: SparkSession, d: str) -> DataFrame:
    """The rules of the worked example for the four most frequent brands of orders."""
    return rules_of_four(view(spark, d, "order_brand", 4))


def worked_example_bounds(spark: SparkSession, d: str) -> DataFrame:
    """The bounds of the worked example for the four most frequent items of a user's day."""
    return bounds_of_four(view(spark, d, "userday", 4))


def item_supports(spark: SparkSession, d: str) -> DataFrame:
    return baskets.item_supports(workloads.order_brand(spark, d))


def _subsets_of_size(db: Database, k: int) -> DataFrame:
    ids = db.baskets.sparkSession.range(1).select(F.sequence(F.lit(0), F.lit(db.n_items - 1)).alias("items"))
    return ids.select(F.explode(k_subsets(F.col("items"), k)).alias("items"))


def _set_supports(view_name: str, k: int, strategy: str, n: int | None = None) -> Query:
    def query(spark: SparkSession, d: str) -> DataFrame:
        db = view(spark, d, view_name, n)
        return _named(db, support.count(db, _subsets_of_size(db, k), k, strategy).where("support > 0"), "support")

    return query


def pattern_weights(spark: SparkSession, d: str) -> DataFrame:
    db = view(spark, d, "userday", None)
    return _named(db, db.baskets, "weight")


def basket_projection(spark: SparkSession, d: str) -> DataFrame:
    db = view(spark, d, "order_brand", None)
    cut = fractions._projected(db, list(range(4))).groupBy(F.col("base").alias("items")).agg(F.sum("weight").alias("cnt"))
    return _named(db, cut, "cnt")


def fractions_3(spark: SparkSession, d: str) -> DataFrame:
    db = view(spark, d, "order_attr", None)
    return db.named(fractions.table(db, [0, 1, 2]), "base")


def support_from_fractions(spark: SparkSession, d: str) -> DataFrame:
    db = view(spark, d, "order_attr", None)
    return _named(db, fractions.to_supports(fractions.table(db, [0, 1, 2])), "support")


def cover_identity(spark: SparkSession, d: str) -> DataFrame:
    db = view(spark, d, "order_brand", None)
    parts = [fractions.covers(db, [i], [j for j in range(6) if j != i]).select(F.array(F.lit(i)).alias("items"), "*") for i in range(6)]
    return _named(db, _union(parts), "union_size", "support_minus_fraction")


def _lattice(spark: SparkSession, d: str, n: int) -> tuple[Database, DataFrame]:
    db = words(spark, d, n)
    return db, keep(mine_bruteforce(db), "lattice")


def _sigma_rules(depth: int | None) -> Query:
    def query(spark: SparkSession, d: str) -> DataFrame:
        db, supports = _lattice(spark, d, 8)
        known = with_empty_set(supports, db.n_baskets)
        parts = [rules.explain(supports.where(F.size("items") == n).select("items"), known, n, depth).where("depth > 0") for n in range(1, 9)]
        return db.named(db.named(_union(parts).select("items", "base", "depth", "sigma")), "base")

    return query


def _interval_bounds(depth: int | None, kernel: str = "lattice") -> Query:
    def query(spark: SparkSession, d: str) -> DataFrame:
        db, supports = _lattice(spark, d, 8)
        known = with_empty_set(supports, db.n_baskets)
        parts = [rules.bounds(supports.where(F.size("items") == n).select("items"), known, n, depth, kernel) for n in range(1, 9)]
        return _named(db, _union(parts), "lower", "upper")

    return query


def derivable_flags(spark: SparkSession, d: str) -> DataFrame:
    return represent.classify(_interval_bounds(None)(spark, d))


def _words_run(spark: SparkSession, d: str, s: int = WORD_SUPPORT, **options) -> Run:
    return mine_nonderivable(words(spark, d), s, **options)


def _nonderivable_words(*columns: str, s: int = WORD_SUPPORT, **options) -> Query:
    def query(spark: SparkSession, d: str) -> DataFrame:
        run = _words_run(spark, d, s, **options)
        return _named(run.db, run.sets, "support", *columns)

    return query


def _nonderivable_view(name: str) -> Query:
    def query(spark: SparkSession, d: str) -> DataFrame:
        db = view(spark, d, name)
        share = oracles.VIEW_SHARES.get(name, 0.01)
        run = mine_nonderivable(db, baskets.resolve_support(share, db.n_baskets))
        return _named(db, run.sets, "support", "lower", "upper")

    return query


def nonderivable_order_fd(spark: SparkSession, d: str) -> DataFrame:
    db = baskets.encode(workloads.order_fd(spark, d), only=workloads.FD_ITEMS)
    return _named(db, mine_nonderivable(db, 150).sets, "support", "lower", "upper")


def derive_derivable(spark: SparkSession, d: str) -> DataFrame:
    run = _words_run(spark, d)
    return _named(run.db, derive.derivable(run), "support")


def _all_from_representation(inherit: bool = True, **options) -> Query:
    def query(spark: SparkSession, d: str) -> DataFrame:
        run = _words_run(spark, d, **options)
        return _named(run.db, derive.all_frequent(run, inherit=inherit).sets, "support")

    return query


def all_frequent_levelwise(spark: SparkSession, d: str) -> DataFrame:
    db = words(spark, d)
    return _named(db, mine_all_levelwise(db, WORD_SUPPORT).sets, "support")


def all_frequent_fpgrowth(spark: SparkSession, d: str) -> DataFrame:
    db = words(spark, d)
    return _named(db, mine_all_fpgrowth(db, WORD_SUPPORT), "support")


def lookup_support(spark: SparkSession, d: str) -> DataFrame:
    run = _words_run(spark, d)
    wanted = spark.createDataFrame([(ids,) for ids in oracles.LOOKED_UP], "items array<int>")
    return _named(run.db, derive.lookup(run, wanted), "status", "support")


def _frequent_words(spark: SparkSession, d: str) -> tuple[Database, DataFrame]:
    db = words(spark, d)
    return db, keep(mine_bruteforce(db).where(F.col("support") >= WORD_SUPPORT), "frequent")


def free_sets(spark: SparkSession, d: str) -> DataFrame:
    db, frequent = _frequent_words(spark, d)
    return _named(db, related.free_sets(frequent, db.n_baskets), "support")


def _disjunction_free(depth: int | None) -> Query:
    def query(spark: SparkSession, d: str) -> DataFrame:
        db, frequent = _frequent_words(spark, d)
        return _named(db, related.disjunction_free(frequent, db.n_baskets, db.n_items, depth), "support")

    return query


def closed_sets(spark: SparkSession, d: str) -> DataFrame:
    db, frequent = _frequent_words(spark, d)
    return _named(db, related.closed_sets(frequent), "support")


def maximal_sets(spark: SparkSession, d: str) -> DataFrame:
    db, frequent = _frequent_words(spark, d)
    return _named(db, related.maximal_sets(frequent), "support")


def counting_inference(spark: SparkSession, d: str) -> DataFrame:
    db = words(spark, d)
    return _named(db, mine_counting_inference(db, WORD_SUPPORT), "support", "inferred")


def lookahead_maximal(spark: SparkSession, d: str) -> DataFrame:
    db = words(spark, d)
    return _named(db, mine_maximal_lookahead(db, WORD_SUPPORT), "support")


def witness_recount(spark: SparkSession, d: str) -> DataFrame:
    db, supports = _lattice(spark, d, 4)
    known = keep(with_empty_set(supports, db.n_baskets), "known")
    whole = supports.where(F.size("items") == 4).select("items")
    found = rules.bounds(whole, known, 4)
    parts = []
    for side in ("lower", "upper"):
        cells = keep(fractions.witness(whole, known, 4, found.select("items", F.col(side).alias("v"))).select(F.col("basket").alias("items"), "weight"), "witness")
        again = support.count(Database(cells, db.items, db.n_baskets, 4), supports, 4, "scan")
        parts.append(again.join(F.broadcast(found.select(F.col(side).alias("v")))).select("items", "v", "support"))
    return _named(db, _union(parts), "v", "support")


def width_by_size(spark: SparkSession, d: str) -> DataFrame:
    return measures.width_by_size(_words_run(spark, d)).withColumn("mean_width", F.round("mean_width", 6))


def funnel(spark: SparkSession, d: str) -> DataFrame:
    return measures.funnel(_words_run(spark, d))


def rule_work(spark: SparkSession, d: str) -> DataFrame:
    return measures.rule_work(_words_run(spark, d))


def derivation_work(spark: SparkSession, d: str) -> DataFrame:
    return measures.derivation_work(spark, derive.all_frequent(_words_run(spark, d)))


def scans_by_method(spark: SparkSession, d: str) -> DataFrame:
    return measures.scans_by_method(words(spark, d), WORD_SUPPORT)


def representation_sizes(spark: SparkSession, d: str) -> DataFrame:
    return measures.representation_sizes(words(spark, d), WORD_SUPPORT)


def size_by_threshold(spark: SparkSession, d: str) -> DataFrame:
    found = measures.size_by_threshold(words(spark, d), [500, 400, 300])
    return found.withColumn("threshold", F.col("threshold").cast("int"))


def size_by_depth(spark: SparkSession, d: str) -> DataFrame:
    return measures.size_by_depth(words(spark, d), WORD_SUPPORT)


def gain_by_depth(spark: SparkSession, d: str) -> DataFrame:
    db, supports = _lattice(spark, d, 8)
    found = measures.bounds_by_depth(supports, db.n_baskets, 8, [1, 2, 3, 4, 8])
    return found.groupBy(F.col("max_depth").alias("depth")).agg(F.round(F.avg(F.col("upper") - F.col("lower")), 6).alias("mean_width"))


def monotone_vs_full_upper(spark: SparkSession, d: str) -> DataFrame:
    db, supports = _lattice(spark, d, 8)
    found = measures.bounds_by_depth(supports, db.n_baskets, 8, [1, 8])
    at = lambda depth: F.round(F.avg(F.when(F.col("max_depth") == depth, F.col("upper"))), 6)
    return found.groupBy("k").agg(at(1).alias("mean_depth1_upper"), at(8).alias("mean_full_upper"))


def whole_view(spark: SparkSession, d: str, name: str, share: float) -> tuple[Database, int]:
    """A view with all its frequent items (the others are in no frequent set), and the threshold as a number of baskets."""
    rows = keep(workloads.VIEWS[name](spark, d), f"view-{name}")
    least = baskets.resolve_support(share, rows.count())
    return baskets.encode(rows, least), least


def _frequent3(name: str, share: float) -> Query:
    def query(spark: SparkSession, d: str) -> DataFrame:
        db, least = whole_view(spark, d, name, share)
        return _named(db, derive.all_frequent(mine_nonderivable(db, least), max_size=3).sets.where("k <= 3"), "support")

    return query


def _exp_width_by_size(name: str, share: float) -> Query:
    """Mean interval width of the candidates of each size, over all frequent items of a view."""

    def query(spark: SparkSession, d: str) -> DataFrame:
        db, least = whole_view(spark, d, name, share)
        return measures.width_by_size(mine_nonderivable(db, least)).withColumn("mean_width", F.round("mean_width", 6))

    return query


def _exp_size_by_threshold(name: str, shares: tuple[float, ...]) -> Query:
    """Sizes of the summary and of all frequent itemsets at falling thresholds, over all items frequent at the lowest one."""

    def query(spark: SparkSession, d: str) -> DataFrame:
        db, _ = whole_view(spark, d, name, min(shares))
        counts = {s: baskets.resolve_support(s, db.n_baskets) for s in shares}
        found = measures.size_by_threshold(db, sorted({c for c in counts.values() if c > 1}))
        named = spark.createDataFrame([(s, c) for s, c in counts.items()], "share double, threshold long")
        return named.join(found, "threshold").select("share", "threshold", "all_cnt", "kept_cnt")

    return query


def derived_equals_counted(spark: SparkSession, d: str) -> DataFrame:
    run = _words_run(spark, d)
    return _named(run.db, checks.derived_not_counted(run.db, derive.all_frequent(run).sets), "support")


def projection_invariance(spark: SparkSession, d: str) -> DataFrame:
    db = view(spark, d, "order_brand", None)
    return _named(db, checks.projection_differs(db, [0, 2, 3, 7]), "support")


def inclusion_exclusion(spark: SparkSession, d: str) -> DataFrame:
    db = view(spark, d, "order_attr", None)
    counted = _union([support.count(db, spark.range(1).select(F.explode(k_subsets(F.array(F.lit(0), F.lit(1), F.lit(2)), k)).alias("items")), k) for k in (1, 2, 3)])
    return db.named(checks.inclusion_exclusion(keep(with_empty_set(counted, db.n_baskets), "counted"), [0, 1, 2]), "base")


def both_bases_exact(spark: SparkSession, d: str) -> DataFrame:
    db, supports = _lattice(spark, d, 8)
    known = with_empty_set(supports, db.n_baskets)
    found = _union([rules.bounds(supports.where(F.size("items") == n).select("items"), known, n) for n in range(1, 9)])
    return db.named(db.named(checks.inherited_not_exact(keep(found, "bounded"), known)), "base")


def border_of_free_sets(spark: SparkSession, d: str) -> DataFrame:
    db, frequent = _frequent_words(spark, d)
    free = keep(related.free_sets(frequent, db.n_baskets), "free")
    return db.named(related.border(free, db.n_items, db.items.select(F.array("item_id").alias("items"))).select("items"))


def constrained_sets(spark: SparkSession, d: str) -> DataFrame:
    run = _words_run(spark, d)
    return _named(run.db, represent.select(run.sets, must=[0], without=[1], min_size=2, max_size=3, min_support=300, max_support=400, max_width=200), "support")


def containment_predicates(spark: SparkSession, d: str) -> DataFrame:
    three = F.array(F.lit(0), F.lit(1), F.lit(2))
    tests = {"holds_all": contains_all, "holds_any": contains_any, "holds_none": contains_none, "is_equal": same_items}
    return words(spark, d).baskets.agg(*[F.coalesce(F.sum(F.when(t(F.col("items"), three), F.col("weight"))), F.lit(0)).alias(n) for n, t in tests.items()])


QUERIES: dict[str, Query] = {
    f.__name__: f
    for f in (
        worked_example_rules, worked_example_bounds, item_supports, pattern_weights, basket_projection, fractions_3, support_from_fractions, cover_identity, derivable_flags, nonderivable_order_fd,
        derive_derivable, all_frequent_levelwise, all_frequent_fpgrowth, lookup_support, free_sets, closed_sets, maximal_sets, counting_inference, lookahead_maximal, witness_recount, width_by_size, funnel,
        rule_work, derivation_work, scans_by_method, representation_sizes, size_by_threshold, size_by_depth, gain_by_depth, monotone_vs_full_upper, derived_equals_counted, projection_invariance, inclusion_exclusion, both_bases_exact, border_of_free_sets,
        constrained_sets, containment_predicates,
    )
}
QUERIES |= {
    "pair_supports": _set_supports("order_brand", 2, "auto"),
    "triple_supports": _set_supports("userday", 3, "auto"),
    "bitmap_supports": _set_supports("order_brand", 2, "bitmap"),
    **{f"count_{s}": _set_supports("doc_word", 3, s, 10) for s in support.STRATEGIES},
    "sigma_rules_depth1": _sigma_rules(1),
    "sigma_rules_depth2": _sigma_rules(2),
    "sigma_rules_all": _sigma_rules(None),
    **{f"interval_bounds_{f'depth{k}' if k else 'full'}": _interval_bounds(k) for k in (1, 2, 3, 4, None)},
    **{f"interval_bounds_{kernel}": _interval_bounds(3, kernel) for kernel in ("relational", "arrow")},
    "nonderivable_words": _nonderivable_words("lower", "upper"),
    "nonderivable_depth0": all_frequent_levelwise,
    **{f"nonderivable_depth{k}": _nonderivable_words(max_depth=k) for k in (1, 2, 3)},
    "nonderivable_no_equality": _nonderivable_words(max_depth=1, equality_prune=False),
    "nonderivable_prune_upper": _nonderivable_words(s=400, prune_upper=True),
    **{f"nonderivable_{name}": _nonderivable_view(name) for name in oracles.MINED_VIEWS},
    **{f"frequent3_{name}": _frequent3(name, share) for name, share in oracles.WHOLE_VIEWS.items()},
    **{f"exp_width_by_size_{name}": _exp_width_by_size(name, oracles.WHOLE_VIEWS[name]) for name in ("order_part", "order_brand", "userday", "order_attr", "doc_word")},
    **{f"exp_size_by_threshold_{name}": _exp_size_by_threshold(name, (0.1, 0.05, 0.02, 0.01, 0.005, 0.002, 0.001)) for name in ("order_part", "order_brand", "userday", "order_attr")},
    "exp_size_by_threshold_doc_word": _exp_size_by_threshold("doc_word", (0.6, 0.5, 0.45, 0.42)),
    "all_frequent_from_representation": _all_from_representation(),
    "all_frequent_without_inheritance": _all_from_representation(inherit=False),
    "all_frequent_from_depth1": _all_from_representation(max_depth=1),
    "all_frequent_from_depth2": _all_from_representation(max_depth=2),
    "disjunction_free": _disjunction_free(2),
    "generalised_disjunction_free": _disjunction_free(None),
}
