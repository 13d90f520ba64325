"""The worked example, the rule table, and what theory promises, on small databases."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from supportbounds import queries, relational, workloads
from supportbounds.operators import baskets, fractions, related, rules, support
from supportbounds.plans import checks, derive, represent
from supportbounds.plans.levelwise import max_level, mine, mine_all_fpgrowth, mine_all_levelwise, mine_bruteforce, mine_counting_inference, mine_maximal_lookahead, with_empty_set


def db_of(spark, rows, **options):
    return baskets.encode(spark.createDataFrame([(i, list(r)) for i, r in enumerate(rows)], "basket_id int, items array<string>"), **options)


def brute(rows, s):
    """All frequent itemsets (names in a frozenset) with supports."""
    items = sorted({x for r in rows for x in r})
    out = {}
    for k in range(1, len(items) + 1):
        for c in itertools.combinations(items, k):
            n = sum(set(c) <= set(r) for r in rows)
            if n >= s:
                out[frozenset(c)] = n
    return out


def as_dict(db, df):
    return {frozenset(r["items"].split()): r["support"] for r in db.named(df.select("items", "support")).collect()}


def random_rows(seed):
    rnd = random.Random(seed)
    items = "abcdef"[: rnd.randint(3, 6)]
    rows = []
    for _ in range(rnd.randint(4, 40)):
        base = [x for x in items if rnd.random() < 0.6]
        rows.append([*base, "b"] if "a" in base and "b" not in base and rnd.random() < 0.8 else base)
    return rows


WORKED = ["A B C", "A C D", "A B D", "C D", "B C D", "A D", "B D", "B C D", "B C D", "A B C D"]


def given(spark, folder, rows):
    """Tables of the given form in which the brands of orders, the items of user-days and flags of lines are these baskets."""
    pairs = [(i, x) for i, r in enumerate(rows) for x in r.split()]
    spark.createDataFrame([(i, "ABCD".index(x)) for i, x in pairs], "l_orderkey long, l_partkey long").write.parquet(f"{folder}/orders-of/lineitem.parquet")
    spark.createDataFrame(list(enumerate("ABCD")), "p_partkey long, p_brand string").write.parquet(f"{folder}/orders-of/part.parquet")
    events = spark.createDataFrame([(i, x, None) for i, x in pairs], "user_id long, event_type string, props string").withColumn("ts", F.lit("2024-01-01").cast("timestamp_ntz"))
    events.write.parquet(f"{folder}/days-of/events.parquet")
    flags = [(10.0 * ("A" in r), 0.05 * ("B" in r), 0.05 * ("C" in r), "N" if "D" in r else "R") for r in rows]
    spark.createDataFrame(flags, "l_quantity double, l_discount double, l_tax double, l_returnflag string").write.parquet(f"{folder}/lines-of/lineitem.parquet")
    return [f"{folder}/{x}" for x in ("orders-of", "days-of", "lines-of")]


def test_worked_example_bounds(spark):
    found = {r.max_depth: (r.lower, r.upper) for r in queries.bounds_of_four(baskets.encode(workloads.worked_example(spark))).collect()}
    assert found == {1: (0, 2), 2: (1, 2), 3: (1, 1), 4: (1, 1)}


def test_worked_example_rules(spark):
    found = {"".join(sorted(r.base.split())): (r.side, r.sigma) for r in queries.rules_of_four(baskets.encode(workloads.worked_example(spark))).collect()}
    lower = {"": 1, "AB": 1, "AC": 1, "AD": 0, "BC": 1, "BD": 0, "CD": 0, "ABCD": 0}
    upper = {"A": 1, "B": 1, "C": 1, "D": 1, "ABC": 2, "ABD": 2, "ACD": 2, "BCD": 4}
    assert found == {k: ("lower", v) for k, v in lower.items()} | {k: ("upper", v) for k, v in upper.items()}


@pytest.mark.parametrize("rows", [WORKED, [*WORKED[:-1], "A C", "A B C"]])
def test_examples_follow_the_given_tables(spark, tmp_path, rows):
    orders, days, lines = given(spark, tmp_path, rows)
    held = [set(r.split()) for r in rows]
    support = lambda x: sum(set(x) <= r for r in held)
    sigma = {}
    for base in ("".join(c) for k in range(4) for c in itertools.combinations("ABCD", k)):
        rest = [x for x in "ABCD" if x not in base]
        sigma[base] = sum((-1) ** (len(rest) - k + 1) * support(base + "".join(c)) for k in range(len(rest)) for c in itertools.combinations(rest, k))
    found = {"".join(sorted(r.base.split())): r.sigma for r in queries.worked_example_rules(spark, orders).collect()}
    assert found == sigma | {"ABCD": 0}
    want = {}
    for depth in (1, 2, 3, 4):
        low, high = ([v for b, v in sigma.items() if 4 - len(b) <= depth and (4 - len(b)) % 2 == odd] for odd in (0, 1))
        want[depth] = max([0, *low]), min(high)
    assert {r.max_depth: (r.lower, r.upper) for r in queries.worked_example_bounds(spark, days).collect()} == want
    by_mask = {sum(1 << "ABCD".index(x) for x in b): v for b, v in sigma.items()}
    assert {r.base_mask: r.sigma for r in relational.sql_bounds(spark, lines).collect()} == by_mask


def test_worked_example_mining(spark):
    db = baskets.encode(workloads.worked_example(spark))
    run = mine(db, 1)
    assert [(v.k, v.generated) for v in run.levels] == [(1, 4), (2, 6), (3, 1)]
    kept = as_dict(db, run.sets)
    assert len(kept) == 11 and kept[frozenset("ABC")] == 2
    everything = as_dict(db, derive.all_frequent(run).sets)
    assert len(everything) == 15 and everything[frozenset("ABCD")] == 1
    assert mine(db, 1, max_depth=1).sets.count() == 15
    assert mine(db, 1, max_depth=2).sets.count() == 11


def test_rule_table_of_four():
    rows = list(rules.template_rows(4))
    assert len({r[1] for r in rows}) == 15 and len(rows) == 3**4 - 2**4
    assert rules.rule_counts(4) == (15, 65) and rules.rule_counts(4, 2) == (10, 4 + 6 * 3)
    with pytest.raises(ValueError, match="16"):
        rules._check(17)


@pytest.mark.parametrize("seed", range(4))
def test_random_databases(spark, seed):
    rows, s = random_rows(seed), 1 + seed
    db = db_of(spark, rows)
    want = brute(rows, s)
    for depth in (None, 1, 2):
        run = mine(db, s, max_depth=depth)
        assert as_dict(db, derive.all_frequent(run).sets) == want, depth
        assert checks.too_long(run, max_level(db.n_baskets, s, depth)).count() == 0
    assert as_dict(db, mine_all_levelwise(db, s).sets) == want
    assert as_dict(db, mine_all_fpgrowth(db, s)) == want
    assert as_dict(db, mine_counting_inference(db, s)) == want
    tops = {x: n for x, n in want.items() if not any(x < y for y in want)}
    assert as_dict(db, mine_maximal_lookahead(db, s)) == tops


def test_theorems_on_all_subsets(spark):
    rows = random_rows(11)
    db = db_of(spark, rows)
    supports = mine_bruteforce(db).cache()
    known = with_empty_set(supports, db.n_baskets)
    by_kernel = {}
    for kernel in rules.KERNELS:
        parts = [rules.bounds(supports.where(F.size("items") == n).select("items"), known, n, None, kernel) for n in range(1, db.n_items + 1)]
        found = parts[0]
        for p in parts[1:]:
            found = found.unionByName(p)
        by_kernel[kernel] = {tuple(r["items"]): (r.lower, r.upper, tuple(r.lower_base), tuple(r.upper_base)) for r in found.collect()}
        if kernel == "lattice":
            assert checks.unsound(found, supports).count() == 0
            assert checks.not_halved(found, supports).count() == 0
            assert checks.derivable_not_monotone(found).count() == 0
    assert by_kernel["lattice"] == by_kernel["arrow"] == by_kernel["relational"]
    whole = list(range(db.n_items))
    sets = spark.range(1).select(F.array(*map(F.lit, whole)).alias("items"))
    assert checks.gap_differs(db, sets, known, whole).count() == 0


def test_witness_is_non_negative_within_bounds_only(spark):
    db = db_of(spark, random_rows(5))
    known = with_empty_set(mine_bruteforce(db), db.n_baskets).cache()
    sets = spark.range(1).select(F.array(F.lit(0), F.lit(1), F.lit(2)).alias("items"))
    low, high = rules.bounds(sets, known, 3).select("lower", "upper").first()
    for v in range(low - 1, high + 2):
        least = fractions.witness(sets, known, 3, sets.withColumn("v", F.lit(v).cast("long"))).agg(F.min("weight")).first()[0]
        assert (least >= 0) == (low <= v <= high)


def test_counting_strategies_agree(spark):
    db = db_of(spark, random_rows(2))
    sets = mine_bruteforce(db).where(F.size("items") == 2)
    want = as_dict(db, sets)
    for strategy in support.STRATEGIES:
        assert as_dict(db, support.count(db, sets.select("items"), 2, strategy)) == want, strategy


@pytest.mark.parametrize("rows", [[], [["a"]], [["a", "b"]] * 5, [[]] * 4, [["a"], ["b"], ["c"]], [["a", "a", None, "b"], ["a"]]])
def test_edge_databases(spark, rows):
    db = db_of(spark, rows)
    clean = [[x for x in r if x] for r in rows]
    assert db.n_baskets == len(rows)
    for s in (1, 2, 100):
        run = mine(db, s)
        assert as_dict(db, derive.all_frequent(run).sets) == brute(clean, s)


def test_related_and_saved(spark, tmp_path):
    rows = random_rows(7)
    db = db_of(spark, rows)
    run = mine(db, 2)
    frequent = derive.all_frequent(run).sets.select("items", "support").cache()
    want = brute(rows, 2)
    subsets = lambda x: [x - {i} for i in x]
    sup = want | {frozenset(): len(rows)}
    free = {x for x in want if all(sup[y] != want[x] for y in subsets(x))}
    closed = {x for x in want if not any(x < y and want[y] == want[x] for y in want)}
    assert set(as_dict(db, related.free_sets(frequent, db.n_baskets))) == free
    assert set(as_dict(db, related.closed_sets(frequent))) == closed
    back = related.supports_from_closed(related.closed_sets(frequent), frequent.select("items"))
    assert as_dict(db, back) == want
    represent.save(run, str(tmp_path / "rep"))
    loaded = represent.load(spark, str(tmp_path / "rep"))
    assert as_dict(loaded.db, derive.all_frequent(loaded).sets) == want
    more = represent.refresh(run, db)
    assert more.db.n_baskets == 2 * db.n_baskets


def test_inconsistent_supports_are_told(spark):
    given = spark.createDataFrame([([], 4), ([0], 3), ([1], 3), ([0, 1], 1)], "items array<int>, support long")
    sets = given.where(F.size("items") == 2).select("items")
    assert rules.bounds(sets, given, 2).select("lower", "upper").first()[:] == (2, 3)
    bad = spark.createDataFrame([([], 4), ([0], 5), ([1], 3)], "items array<int>, support long")
    assert rules.inconsistent(rules.bounds(sets, bad, 2)).count() == 1


def test_thresholds():
    assert baskets.resolve_support(0.001, 41337) == 42
    assert baskets.resolve_support(10, 100) == 10 and baskets.resolve_support(10, 100, strict=True) == 11


def test_derivation_reads_no_baskets(spark):
    db = baskets.encode(workloads.worked_example(spark))
    run = mine(db, 1)
    run.db.baskets = None  # any use would fail
    assert derive.all_frequent(run).sets.count() == 15


def test_lookup_of_long_itemsets(spark):
    names = [f"i{k:02d}" for k in range(17)]
    rows = [names] * 10 + [names[:3]] * 4 + [names[::2]] * 6 + [names[:15]] * 2 + [["x"]] * 3
    db = db_of(spark, rows)
    ids = {r["item"]: r.item_id for r in db.items.collect()}
    wanted = {tuple(sorted(ids[x] for x in w)): w for w in (names, names[:15], names[1::2], names[:2], ["x", names[0]])}
    run = mine(db, 5, max_depth=2)
    found = {tuple(r["items"]): (r.status, r.support) for r in derive.lookup(run, spark.createDataFrame([(list(w),) for w in wanted], "items array<int>")).collect()}
    for w, names_of in wanted.items():
        n = sum(set(names_of) <= set(r) for r in rows)
        assert found[w] == (("frequent", n) if n >= 5 else ("infrequent", None))


def test_bounds_of_long_itemsets_at_limited_depth(spark):
    # 40 items, one basket without each item or pair of items of the first five: supports known by counting
    n, whole = 40, list(range(40))
    sets = spark.range(1).select(F.array(*map(F.lit, whole)).alias("items"))
    missing = [(), (0,), (1,), (0, 1), (2,)]
    dropped = [s for d in (1, 2) for s in itertools.combinations(whole, d)]
    support_of = lambda s: sum(set(m) <= set(s) for m in missing)
    known = spark.createDataFrame([([x for x in whole if x not in s], support_of(s)) for s in dropped], "items array<int>, support long")
    low, high = rules.bounds(sets, known, n, 2).select("lower", "upper").first()
    pairs = [support_of((a,)) + support_of((b,)) - support_of((a, b)) for a, b in itertools.combinations(whole, 2)]
    assert (low, high) == (max(0, *pairs), min(support_of((a,)) for a in whole))
    assert rules.explain(sets, known, n, 2).count() == 1 + 40 + 780


def test_heavy_baskets_are_not_written_out(spark):
    cells = spark.createDataFrame([([0, 1], 10**9), ([1], 3), ([0, 1, 2], 5), ([], 10**12)], "items array<int>, weight long")
    items = spark.createDataFrame([(0, "a", 10**9 + 5), (1, "b", 10**9 + 8), (2, "c", 5)], "item_id int, item string, support long")
    db = baskets.Database(cells, items, 10**12 + 10**9 + 8, 3)
    sets = spark.createDataFrame([([0, 1],), ([1, 2],), ([0, 2],)], "items array<int>")
    for strategy in support.STRATEGIES:
        assert as_dict(db, support.count(db, sets, 2, strategy)) == {frozenset("ab"): 10**9 + 5, frozenset("bc"): 5, frozenset("ac"): 5}, strategy


def test_pairs_counted_from_baskets(spark):
    rows = random_rows(3)
    db = db_of(spark, rows)
    for depth in (None, 1):
        listed, counted = mine(db, 2, max_depth=depth), mine(db, 2, max_depth=depth, listed_pairs=0)
        assert as_dict(db, listed.sets) == as_dict(db, counted.sets)
        assert [v.counted for v in listed.levels] == [v.counted for v in counted.levels]


def test_more_items_than_bits(spark):
    rnd = random.Random(4)
    rows = [[f"n{rnd.randrange(90)}" for _ in range(4)] + ["all"] * (i % 2) for i in range(120)]
    db = db_of(spark, rows)
    assert db.n_items > 62 and db.n_baskets == 120
    want = brute([[x for x in r if x == "all" or x < "n2"] for r in rows], 2)
    found = as_dict(db, mine_all_levelwise(db, 2).sets)
    assert {x: n for x, n in found.items() if all(y == "all" or y < "n2" for y in x)} == want
