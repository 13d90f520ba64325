"""DuckDB SQL that computes what the queries return, by brute force over the masks of at most ten items."""

from __future__ import annotations

from supportbounds.workloads import FD_ITEMS

#: For each view: its (basket, item) pairs, and the ids of all its baskets.
VIEW_SQL = {
    "doc_word": (r"SELECT DISTINCT doc_id AS b, unnest(string_split_regex(lower(coalesce(text, '')), '[^\p{L}\p{N}]+')) AS item FROM documents", "SELECT doc_id AS b FROM documents"),
    "doc_line": ("SELECT DISTINCT doc_id AS b, unnest(string_split(coalesce(text, ''), chr(10))) AS item FROM documents", "SELECT doc_id AS b FROM documents"),
    "conv_word": (r"SELECT DISTINCT conv_id AS b, unnest(string_split_regex(lower(coalesce(text, '')), '[^\p{L}\p{N}]+')) AS item FROM conversations", "SELECT DISTINCT conv_id AS b FROM conversations"),
    "page_tag": ("SELECT DISTINCT page_id AS b, unnest(regexp_extract_all(lower(html), '<([a-z][a-z0-9]*)', 1)) AS item FROM pages", "SELECT page_id AS b FROM pages"),
    "vec_sign": ("SELECT b, 'd' || (i - 1) AS item FROM (SELECT vec_id AS b, unnest(embedding) AS v, generate_subscripts(embedding, 1) AS i FROM embeddings) WHERE v > 0", "SELECT vec_id AS b FROM embeddings"),
    "doc_label": (
        "SELECT doc_id AS b, unnest(['lang=' || lang, 'source=' || source, 'quality=' || quality, 'toxic=' || toxic]) AS item FROM documents JOIN labels USING (doc_id)",
        "SELECT doc_id AS b FROM documents JOIN labels USING (doc_id)",
    ),
    "doc_bench": (
        r"SELECT * FROM (SELECT DISTINCT doc_id AS b, unnest(string_split_regex(lower(coalesce(text, '')), '[^\p{L}\p{N}]+')) AS item FROM documents) WHERE item IN (SELECT unnest(string_split_regex(lower(coalesce(text, '')), '[^\p{L}\p{N}]+')) FROM benchmark)",
        "SELECT doc_id AS b FROM documents",
    ),
    "supplier_nation": (
        "SELECT DISTINCT l_orderkey AS b, unnest([n_name, r_name]) AS item FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey",
        "SELECT DISTINCT l_orderkey AS b FROM lineitem",
    ),
    "order_part": ("SELECT DISTINCT l_orderkey AS b, CAST(l_partkey AS VARCHAR) AS item FROM lineitem", "SELECT DISTINCT l_orderkey AS b FROM lineitem"),
    "order_brand": ("SELECT DISTINCT l_orderkey AS b, p_brand AS item FROM lineitem JOIN part ON l_partkey = p_partkey", "SELECT DISTINCT l_orderkey AS b FROM lineitem"),
    "userday": (
        """SELECT DISTINCT user_id || '@' || strftime(ts, '%Y-%m-%d') AS b, unnest([event_type, 'k' || (CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS INT) // 10)]) AS item FROM events""",
        "SELECT DISTINCT user_id || '@' || strftime(ts, '%Y-%m-%d') AS b FROM events",
    ),
    "order_attr": (
        """SELECT o_orderkey AS b, unnest(['status=' || o_orderstatus, 'priority=' || o_orderpriority, 'segment=' || c_mktsegment, 'region=' || r_name, 'nation=' || n_name,
        'price=' || CAST(least(4, floor(o_totalprice / 100000)) AS INT)]) AS item
        FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey""",
        "SELECT o_orderkey AS b FROM orders",
    ),
    "order_fd": (
        """SELECT o_orderkey AS b, unnest(['status=' || o_orderstatus, 'region=' || r_name, 'nation=' || n_name]) AS item
        FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey""",
        "SELECT o_orderkey AS b FROM orders",
    ),
}
VIEW_SQL["line_attr"] = (
    """SELECT b, unnest(['flag=' || l_returnflag, 'state=' || l_linestatus, 'tax=' || CAST(round(l_tax * 100) AS INT), 'discount=' || CAST(round(l_discount * 100) AS INT),
    'quantity=' || CAST(floor(l_quantity / 10) AS INT), 'brand=' || p_brand, 'type=' || p_type, 'year=' || year(l_shipdate)]) AS item
    FROM (SELECT row_number() OVER () AS b, * FROM lineitem) JOIN part ON l_partkey = p_partkey""",
    "SELECT row_number() OVER () AS b FROM lineitem",
)
VIEW_SQL["session"] = (
    """SELECT DISTINCT user_id || '@' || s AS b, item FROM (SELECT user_id, item, sum(new) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS s
    FROM (SELECT *, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 21600000000 THEN 0 ELSE 1 END AS new
    FROM (SELECT user_id, ts, unnest([event_type, 'k' || (CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS INT) // 10)]) AS item FROM events)))""",
    """SELECT DISTINCT user_id || '@' || s AS b FROM (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS s
    FROM (SELECT *, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 21600000000 THEN 0 ELSE 1 END AS new FROM events))""",
)


def base(view: str, n: int, only: list[str] | None = None) -> str:
    """CTEs: t (id, item, c), nm (names in order), pat (m, w), nb (n), sets (x, k), sup (x, k, s)."""
    pairs, ids = VIEW_SQL[view]
    held = f"WHERE item IN ({', '.join(repr(i) for i in only)})" if only else "WHERE item <> ''"
    return f"""
WITH v AS MATERIALIZED ({pairs}), u AS ({ids}),
t AS MATERIALIZED (SELECT row_number() OVER (ORDER BY c DESC, item) - 1 AS id, item, c FROM (SELECT item, count(*) AS c FROM v {held} GROUP BY item ORDER BY c DESC, item LIMIT {n})),
nm AS MATERIALIZED (SELECT list(item ORDER BY id) AS names, count(*) AS n_items FROM t),
bm AS (SELECT v.b, bit_or(1 << CAST(id AS INT)) AS m FROM v JOIN t USING (item) GROUP BY v.b),
pat AS MATERIALIZED (SELECT coalesce(m, 0) AS m, count(*) AS w FROM u LEFT JOIN bm ON u.b = bm.b GROUP BY 1),
nb AS MATERIALIZED (SELECT CAST(sum(w) AS BIGINT) AS n FROM pat),
sets AS MATERIALIZED (SELECT CAST(range AS INT) AS x, CAST(bit_count(CAST(range AS INT)) AS INT) AS k FROM range(0, 1 << {n}) WHERE range < (SELECT 1 << CAST(n_items AS INT) FROM nm)),
sup AS MATERIALIZED (SELECT x, k, CAST(coalesce(sum(w) FILTER ((m & x) = x), 0) AS BIGINT) AS s FROM sets, pat GROUP BY x, k)"""


def name(x: str) -> str:
    """The names of a mask's items, in order of their ids."""
    return f"(SELECT coalesce(array_to_string(list_filter(list_transform(names, lambda z, nth: CASE WHEN ({x} >> CAST(nth - 1 AS INT)) & 1 = 1 THEN z END), lambda z: z IS NOT NULL), ' '), '') FROM nm)"


def rules(depth: int | None = None) -> str:
    """CTEs sig (j, i, d, sigma) for all depths of one and more, bnd (x, k, s, l, u) up to the depth."""
    at_most = "" if depth is None else f" AND d <= {depth}"
    return f""",
sig AS MATERIALIZED (SELECT j.x AS j, i.x AS i, j.k - i.k AS d, CAST(sum(CASE WHEN (j.k - y.k) % 2 = 1 THEN y.s ELSE -y.s END) AS BIGINT) AS sigma
  FROM sets j JOIN sets i ON (i.x & j.x) = i.x AND i.x <> j.x JOIN sup y ON (y.x & j.x) = y.x AND (y.x & i.x) = i.x AND y.x <> j.x GROUP BY ALL),
bnd AS MATERIALIZED (SELECT sup.x, sup.k, sup.s, greatest(0, coalesce(max(sigma) FILTER (d % 2 = 0{at_most}), 0)) AS l, min(sigma) FILTER (d % 2 = 1{at_most}) AS u
  FROM sup JOIN sig ON sig.j = sup.x GROUP BY ALL)"""


def mined(threshold: str, equality: bool = True) -> str:
    """CTEs lim (s0), flag (x, k, s, l, u, ext), cand (all proper subsets extendable), kept."""
    off = " AND s <> l AND s <> u" if equality else ""
    return f""",
lim AS (SELECT CAST({threshold} AS BIGINT) AS s0 FROM nb),
flag AS MATERIALIZED (SELECT bnd.*, s >= s0 AND l <> u{off} AS ext FROM bnd, lim),
bad AS MATERIALIZED (SELECT DISTINCT f.x FROM flag f JOIN flag y ON (y.x & f.x) = y.x AND y.x <> f.x AND NOT y.ext),
cand AS MATERIALIZED (SELECT * FROM flag WHERE x NOT IN (SELECT x FROM bad)),
kept AS MATERIALIZED (SELECT cand.* FROM cand, lim WHERE s >= s0 AND l <> u)"""


FREQUENT = """,
f AS MATERIALIZED (SELECT sup.* FROM sup, lim WHERE s >= s0 AND k > 0),
below AS MATERIALIZED (SELECT f.x, f.s, y.x AS y, y.s AS ys FROM f JOIN sup y ON (y.x & f.x) = y.x AND y.k = f.k - 1),
free AS MATERIALIZED (SELECT DISTINCT x, s FROM f WHERE x NOT IN (SELECT x FROM below WHERE s = ys)),
closed AS (SELECT x, s FROM f WHERE x NOT IN (SELECT y FROM below WHERE s = ys)),
maximal AS (SELECT x, s FROM f WHERE x NOT IN (SELECT y FROM below))"""


def limit_only(threshold: str) -> str:
    return f", lim AS (SELECT CAST({threshold} AS BIGINT) AS s0 FROM nb)"


def rows(source: str, columns: str = "s AS support", where: str = "") -> str:
    return f"\nSELECT {name('x')} AS items, {columns} FROM {source} {where}"


KEPT = "s AS support, l AS lower, u AS upper"
WORDS = ("doc_word", 10)


def exact_at(depth: int | None) -> str:
    """CTE fr: frequent sets without an exact rule up to the depth."""
    most = "" if depth is None else f" AND d <= {depth}"
    return f", fr{depth or 'g'} AS (SELECT x, s FROM f WHERE x NOT IN (SELECT j FROM sig JOIN sup ON sup.x = j WHERE sigma = s{most}))"


def all_oracles() -> dict[str, str]:
    words8, words10 = base("doc_word", 8), base(*WORDS)
    mined300 = words10 + rules() + mined("300")
    freq300 = words10 + rules() + mined("300") + FREQUENT
    out = {
        "worked_example_rules": base("order_brand", 4) + rules() + f"\nSELECT {name('i')} AS base, CAST(d AS INT) AS depth, CASE WHEN d % 2 = 0 THEN 'lower' ELSE 'upper' END AS side, sigma FROM sig WHERE j = 15 UNION ALL SELECT {name('15')}, 0, 'lower', 0",
        "worked_example_bounds": base("userday", 4) + rules() + "".join(f"\n{'UNION ALL' * (k > 1)} SELECT {k} AS max_depth, greatest(0, coalesce(max(sigma) FILTER (d % 2 = 0 AND d <= {k}), 0)) AS lower, min(sigma) FILTER (d % 2 = 1 AND d <= {k}) AS upper FROM sig WHERE j = 15" for k in (1, 2, 3, 4)),
        "item_supports": "SELECT p_brand AS item, count(DISTINCT l_orderkey) AS support FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand",
        "pair_supports": _self_join("order_brand", 2),
        "bitmap_supports": _self_join("order_brand", 2),
        "triple_supports": _self_join("userday", 3),
        "pattern_weights": base("userday", 15).split(",\nsets AS")[0] + f"\nSELECT {name('m')} AS items, w AS weight FROM pat",
        "basket_projection": base("order_brand", 4) + f"\nSELECT {name('m')} AS items, CAST(w AS BIGINT) AS cnt FROM pat",
        "fractions_3": base("order_attr", 3) + f"\nSELECT {name('x')} AS base, CAST(coalesce(w, 0) AS BIGINT) AS cnt FROM sets LEFT JOIN pat ON m = x",
        "support_from_fractions": base("order_attr", 3) + rows("sup"),
        "cover_identity": base("order_brand", 6) + f"\nSELECT {name('x')} AS items, CAST(sum(w) FILTER ((m & x) = x AND (m & (63 - x)) <> 0) AS BIGINT) AS union_size, CAST(any_value(s) - coalesce(sum(w) FILTER (m = x), 0) AS BIGINT) AS support_minus_fraction FROM sup, pat WHERE k = 1 GROUP BY x",
        "derivable_flags": words8 + rules() + rows("bnd", "l AS lower, u AS upper, l = u AS derivable"),
        "nonderivable_words": mined300 + rows("kept", KEPT),
        "nonderivable_order_fd": base("order_fd", 6, FD_ITEMS) + rules() + mined("150") + rows("kept", KEPT),
        "nonderivable_no_equality": words10 + rules(1) + mined("300", equality=False) + rows("kept"),
        "nonderivable_prune_upper": words10 + rules() + mined("400") + rows("kept"),
        "derive_derivable": mined300 + rows("sup, lim", where="WHERE s >= s0 AND k > 0 AND x NOT IN (SELECT x FROM kept)"),
        "counting_inference": freq300 + rows("f", "s AS support, k > 1 AND x IN (SELECT b.x FROM below b WHERE y <> 0 AND y NOT IN (SELECT x FROM free)) AS inferred"),
        "lookup_support": words10 + limit_only("300") + rows("sup, lim", "CASE WHEN s >= s0 THEN 'frequent' ELSE 'infrequent' END AS status, CASE WHEN s >= s0 THEN s END AS support", f"WHERE x IN ({', '.join(str(sum(1 << i for i in ids)) for ids in LOOKED_UP)})"),
        "representation_sizes": freq300 + exact_at(2) + exact_at(None) + ", d1 AS (SELECT count(*) AS n FROM (" + words10 + rules(1) + mined("300") + "\nSELECT x FROM kept))" + "".join(
            f"\n{'UNION ALL' * bool(i)} SELECT '{kind}' AS kind, {'n' if kind == 'nonderivable_depth1' else 'count(*)'} AS cnt FROM {source}"
            for i, (kind, source) in enumerate({"all": "f", "nonderivable": "kept", "nonderivable_depth1": "d1", "free": "free", "disjunction_free": "fr2", "generalised_disjunction_free": "frg", "closed": "closed", "maximal": "maximal"}.items())
        ),
        "witness_recount": base("doc_word", 4) + rules() + f", e AS (SELECT l AS v FROM bnd WHERE x = 15 UNION ALL SELECT u FROM bnd WHERE x = 15)\nSELECT v, {name('x')} AS items, CASE WHEN x = 15 THEN v ELSE s END AS support FROM sup, e WHERE k > 0",
        "width_by_size": mined300 + "\nSELECT CAST(k AS INT) AS k, count(*) AS candidates, round(avg(u - l), 6) AS mean_width FROM cand GROUP BY k",
        "funnel": mined300 + "\nSELECT CAST(k AS INT) AS k, count(*) AS generated, count(*) FILTER (l = u) AS dropped, count(*) FILTER (l <> u) AS counted, count(*) FILTER (l <> u AND s < s0) AS infrequent, count(*) FILTER (l <> u AND s >= s0 AND NOT ext) AS not_extended FROM cand, lim GROUP BY k",
        "rule_work": mined300 + "\nSELECT CAST(k AS INT) AS k, CAST(count(*) * (pow(2, k) - 1) AS BIGINT) AS rules, CAST(count(*) * (pow(3, k) - pow(2, k)) AS BIGINT) AS terms FROM cand WHERE k > 1 GROUP BY k",
        "scans_by_method": freq300 + "\nSELECT 'levelwise' AS method, CAST(count(DISTINCT k) AS INT) AS scans FROM sup, lim WHERE k > 0 AND x NOT IN (SELECT a.x FROM sup a JOIN sup y ON (y.x & a.x) = y.x AND y.x <> a.x AND y.s < (SELECT s0 FROM lim)) UNION ALL SELECT 'nonderivable', CAST(count(DISTINCT k) AS INT) FROM cand WHERE l <> u UNION ALL SELECT 'derivation', 0",
        "gain_by_depth": words8 + rules() + "".join(f"\n{'UNION ALL' * (d > 1)} SELECT {d} AS depth, round(avg(u - l), 6) AS mean_width FROM (SELECT j, greatest(0, coalesce(max(sigma) FILTER (d % 2 = 0 AND d <= {d}), 0)) AS l, min(sigma) FILTER (d % 2 = 1 AND d <= {d}) AS u FROM sig GROUP BY j)" for d in (1, 2, 3, 4, 8)),
        "monotone_vs_full_upper": words8 + rules() + "\nSELECT CAST(bit_count(j) AS INT) AS k, round(avg(u1), 6) AS mean_depth1_upper, round(avg(u), 6) AS mean_full_upper FROM (SELECT j, min(sigma) FILTER (d = 1) AS u1, min(sigma) FILTER (d % 2 = 1) AS u FROM sig GROUP BY j) GROUP BY 1",
        "size_by_threshold": words10 + rules() + "".join(f", {chr(97 + i)} AS (SELECT {s} AS threshold, (SELECT count(*) FROM sup WHERE k > 0 AND s >= {s}) AS all_cnt, (SELECT count(*) FROM ({words10 + rules() + mined(str(s))} SELECT x FROM kept)) AS kept_cnt)" for i, s in enumerate((500, 400, 300))) + "\nSELECT * FROM a UNION ALL SELECT * FROM b UNION ALL SELECT * FROM c",
        "size_by_depth": "SELECT 0 AS depth, (SELECT count(*) FROM (" + words10 + "\nSELECT x FROM sup WHERE k > 0 AND s >= 300)) AS kept_cnt" + "".join(f"\nUNION ALL SELECT {k}, (SELECT count(*) FROM ({words10 + rules(k) + mined('300')}\nSELECT x FROM kept))" for k in range(1, 6)),
    }
    for which, source in {"free_sets": "free", "closed_sets": "closed", "maximal_sets": "maximal", "lookahead_maximal": "maximal"}.items():
        out[which] = freq300 + rows(source)
    out["disjunction_free"] = freq300 + exact_at(2) + rows("fr2")
    out["generalised_disjunction_free"] = freq300 + exact_at(None) + rows("frg")
    for which in ("all_frequent_from_representation", "all_frequent_levelwise", "all_frequent_fpgrowth", "nonderivable_depth0", "all_frequent_without_inheritance", "all_frequent_from_depth1", "all_frequent_from_depth2"):
        out[which] = words10 + limit_only("300") + rows("sup, lim", where="WHERE s >= s0 AND k > 0")
    for which in ("expand", "trie", "bitmap", "pattern", "scan", "partitioned", "mask"):
        out[f"count_{which}"] = words10 + rows("sup", where="WHERE k = 3")
    for k in (1, 2, 3):
        out[f"nonderivable_depth{k}"] = words10 + rules(k) + mined("300") + rows("kept")
    for k in (1, 2, 3, 4, None):
        out[f"interval_bounds_{f'depth{k}' if k else 'full'}"] = words8 + rules(k) + rows("bnd", "l AS lower, u AS upper")
    for which in ("relational", "arrow"):
        out[f"interval_bounds_{which}"] = words8 + rules(3) + rows("bnd", "l AS lower, u AS upper")
    for which, d in {"depth1": 1, "depth2": 2, "all": 8}.items():
        out[f"sigma_rules_{which}"] = words8 + rules() + f"\nSELECT {name('j')} AS items, {name('i')} AS base, CAST(d AS INT) AS depth, sigma FROM sig WHERE d <= {d}"
    out["border_of_free_sets"] = freq300 + rows("sup", "0 AS unused", "WHERE k > 0 AND x NOT IN (SELECT x FROM free) AND x NOT IN (SELECT a.x FROM sup a JOIN sup y ON (y.x & a.x) = y.x AND y.x <> a.x AND y.k > 0 WHERE y.x NOT IN (SELECT x FROM free))").replace(", 0 AS unused", "")
    out["inclusion_exclusion"] = out["fractions_3"]
    nothing = "SELECT '' AS items, CAST(0 AS BIGINT) AS support WHERE false"
    out["derived_equals_counted"] = out["projection_invariance"] = nothing
    out["both_bases_exact"] = "SELECT '' AS items, '' AS base WHERE false"
    out["constrained_sets"] = mined300 + rows("kept", "s AS support", "WHERE (x & 1) = 1 AND (x & 2) = 0 AND k BETWEEN 2 AND 3 AND s BETWEEN 300 AND 400 AND u - l <= 200")
    out["containment_predicates"] = words10 + "\nSELECT CAST(coalesce(sum(w) FILTER ((m & 7) = 7), 0) AS BIGINT) AS holds_all, CAST(coalesce(sum(w) FILTER ((m & 7) <> 0), 0) AS BIGINT) AS holds_any, CAST(coalesce(sum(w) FILTER ((m & 7) = 0), 0) AS BIGINT) AS holds_none, CAST(coalesce(sum(w) FILTER (m = 7), 0) AS BIGINT) AS is_equal FROM pat"
    for view, share in WHOLE_VIEWS.items():
        out[f"frequent3_{view}"] = frequent3(view, share)
    for view in MINED_VIEWS:
        share = f"ceil(n * {VIEW_SHARES.get(view, 0.01)} - 1e-9)"
        out[f"nonderivable_{view}"] = base(view, 10) + rules() + mined(share) + rows("kept", KEPT)
    return out


#: Views mined whole, with all their frequent items, and the share of baskets that is frequent.
WHOLE_VIEWS = {"order_part": 0.0002, "order_brand": 0.01, "userday": 0.01, "session": 0.01, "order_attr": 0.01, "line_attr": 0.01, "doc_word": 0.42, "doc_label": 0.02, "supplier_nation": 0.02}


def frequent3(view: str, share: float) -> str:
    """All frequent itemsets of one to three items, over all items, by self-joins."""
    pairs, ids = VIEW_SQL[view]
    sizes = []
    for k in (1, 2, 3):
        joins = " ".join(f"JOIN e e{i} ON e{i}.b = e{i - 1}.b AND e{i}.id > e{i - 1}.id" for i in range(1, k))
        items = " || ' ' || ".join(f"e{i}.item" for i in range(k))
        sizes.append(f"SELECT {items} AS items, count(*) AS support FROM e e0 {joins} GROUP BY {', '.join(f'e{i}.item' for i in range(k))} HAVING count(*) >= (SELECT s FROM lim)")
    return f"""WITH v AS MATERIALIZED ({pairs}), u AS ({ids}), lim AS MATERIALIZED (SELECT greatest(1, ceil(count(*) * {share} - 1e-9)) AS s FROM u),
t AS MATERIALIZED (SELECT item, row_number() OVER (ORDER BY count(*) DESC, item) AS id FROM v WHERE item <> '' GROUP BY item HAVING count(*) >= (SELECT s FROM lim)),
e AS MATERIALIZED (SELECT b, id, item FROM v JOIN t USING (item))
""" + "\nUNION ALL ".join(sizes)


#: Views mined at one per cent of their baskets, top ten items.
MINED_VIEWS = ("order_attr", "order_brand", "order_part", "userday", "doc_line", "conv_word", "page_tag", "doc_label", "vec_sign", "doc_bench", "supplier_nation", "line_attr")
#: Other shares: single parts are rare.
VIEW_SHARES = {"order_part": 0.001}
#: Ids of itemsets of the words view that are looked up: frequent and infrequent ones, short and long.
LOOKED_UP = ([0], [0, 1], [8, 9], [0, 1, 2], [5, 7, 9], [0, 1, 2, 3], [6, 7, 8, 9], [0, 2, 4, 6, 8], [0, 1, 2, 3, 4, 5, 6, 7, 8, 9])


def _self_join(view: str, k: int) -> str:
    pairs, _ = VIEW_SQL[view]
    joins = " ".join(f"JOIN e e{i} ON e{i}.b = e{i - 1}.b AND e{i}.id > e{i - 1}.id" for i in range(1, k))
    items = " || ' ' || ".join(f"e{i}.item" for i in range(k))
    return f"""WITH v AS ({pairs}), t AS (SELECT item, row_number() OVER (ORDER BY count(*) DESC, item) AS id FROM v GROUP BY item), e AS (SELECT b, id, item FROM v JOIN t USING (item))
SELECT {items} AS items, count(*) AS support FROM e e0 {joins} GROUP BY ALL"""
