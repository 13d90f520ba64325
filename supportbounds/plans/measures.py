"""Cost and accuracy measures, and the experiments that vary one parameter."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from supportbounds.operators import related, rules
from supportbounds.operators.baskets import Database
from supportbounds.plans import derive
from supportbounds.plans.levelwise import Run, _union, mine_all_levelwise, mine_nonderivable, with_empty_set


def width_by_size(run: Run) -> DataFrame:
    """(k, candidates, mean_width) over all candidates for which an interval was deduced, derivable ones too."""
    return run.candidates.groupBy("k").agg(F.count("*").alias("candidates"), F.avg(F.col("upper") - F.col("lower")).alias("mean_width"))


def size_by_threshold(db: Database, thresholds: list[int], max_depth: int | None = None) -> DataFrame:
    """(threshold, all_cnt, kept_cnt): one row per threshold, counted on the two results."""
    parts = []
    for s in thresholds:
        every = mine_all_levelwise(db, s).sets.agg(F.count("*").alias("all_cnt"))
        kept = mine_nonderivable(db, s, max_depth=max_depth).sets.agg(F.count("*").alias("kept_cnt"))
        parts.append(every.crossJoin(kept).select(F.lit(s).cast("long").alias("threshold"), "all_cnt", "kept_cnt"))  # one row each
    return _union(parts)


def run_at_depth(db: Database, min_support: int, depth: int) -> Run:
    """Depth 0 is mining by monotonicity alone; depth 1 and more use the rules and the equality test."""
    return mine_all_levelwise(db, min_support) if depth == 0 else mine_nonderivable(db, min_support, max_depth=depth)


def size_by_depth(db: Database, min_support: int, depths: range = range(6)) -> DataFrame:
    return _union([run_at_depth(db, min_support, k).sets.agg(F.lit(k).alias("depth"), F.count("*").alias("kept_cnt")) for k in depths])


def time_by_depth(db: Database, min_support: int, depths: range = range(6)) -> list[dict]:
    """Seconds for the representation alone, and with all other frequent sets derived from it; no row is kept from before."""
    out = []
    for k in depths:
        began = time.time()
        run = run_at_depth(db, min_support, k)
        mined = time.time() - began
        n_kept = run.sets.count()
        began = time.time()
        n_all = derive.all_frequent(run).sets.count() if k else n_kept
        out.append({"depth": k, "kept": n_kept, "all": n_all, "scans": run.scans, "mine_s": round(mined, 3), "mine_and_derive_s": round(mined + (time.time() - began) * (k > 0), 3)})
    return out


def funnel(run: Run) -> DataFrame:
    rows = [(v.k, v.generated, v.dropped, v.counted, v.infrequent, v.not_extended) for v in run.levels]
    return run.sets.sparkSession.createDataFrame(rows, "k int, generated long, dropped long, counted long, infrequent long, not_extended long")


def rule_work(run: Run) -> DataFrame:
    """(k, rules, terms): evaluated for the candidates of each size from 2 on."""
    rows = []
    for v in run.levels:
        if v.k > 1:
            n_rules, n_terms = rules.rule_counts(v.k, run.max_depth)
            rows.append((v.k, v.generated * n_rules, v.generated * n_terms))
    return run.sets.sparkSession.createDataFrame(rows, "k int, rules long, terms long")


def derivation_work(spark: SparkSession, found: derive.Derivation) -> DataFrame:
    rows = [(k, found.inherited[k], found.evaluated[k]) for k in sorted(found.inherited)]
    return spark.createDataFrame(rows, "k int, inherited long, evaluated long")


def scans_by_method(db: Database, min_support: int) -> DataFrame:
    """(method, scans): passes over the baskets; deriving the rest takes none."""
    rows = [("levelwise", mine_all_levelwise(db, min_support).scans), ("nonderivable", mine_nonderivable(db, min_support).scans), ("derivation", 0)]
    return db.baskets.sparkSession.createDataFrame(rows, "method string, scans int")


def representation_sizes(db: Database, min_support: int) -> DataFrame:
    """(kind, cnt): sizes of all summaries of one input."""
    run = mine_nonderivable(db, min_support)
    every = derive.all_frequent(run).sets.select("items", "support")
    longest = every.agg(F.max(F.size("items"))).first()[0] or 0
    n = db.n_baskets
    kinds = {
        "all": every, "nonderivable": run.sets, "nonderivable_depth1": mine_nonderivable(db, min_support, max_depth=1).sets, "free": related.free_sets(every, n),
        "disjunction_free": related.disjunction_free(every, n, longest), "generalised_disjunction_free": related.disjunction_free(every, n, longest, None),
        "closed": related.closed_sets(every), "maximal": related.maximal_sets(every),
    }
    return _union([df.agg(F.lit(kind).alias("kind"), F.count("*").alias("cnt")) for kind, df in kinds.items()])


def bounds_by_depth(supports: DataFrame, n_baskets: int, longest: int, depths: list[int | None]) -> DataFrame:
    """(items, k, max_depth, lower, upper) of every itemset in ``supports`` from 1 to ``longest`` items, for each depth."""
    known = with_empty_set(supports, n_baskets)
    parts = []
    for depth in depths:
        for n in range(1, longest + 1):
            found = rules.bounds(supports.where(F.size("items") == n).select("items"), known, n, depth)
            parts.append(found.select("items", F.lit(n).alias("k"), F.lit(depth).cast("int").alias("max_depth"), "lower", "upper"))
    return _union(parts)
