"""Relational operators around the miner: encoders, joins, grouping sets, windows, set operations, sampling."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from supportbounds import workloads
from supportbounds.operators import joins
from supportbounds.operators.baskets import item_supports
from supportbounds.sources.tables import table

Query = Callable[[SparkSession, str], DataFrame]


def _items(df: DataFrame) -> DataFrame:
    return df.select(F.col("basket_id").alias("id"), F.array_join(F.array_sort("items"), " ").alias("items"))


def basket_lines_per_order(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("id")).agg(F.count("*").alias("n_lines"), F.count_distinct("l_partkey").alias("n_items"))


def attr_items(spark: SparkSession, d: str) -> DataFrame:
    return _items(workloads.order_attr(spark, d))


def word_items(spark: SparkSession, d: str) -> DataFrame:
    return workloads.doc_word(spark, d).select(F.col("basket_id").alias("id"), F.size("items").alias("n_items"))


def json_items(spark: SparkSession, d: str) -> DataFrame:
    k = F.get_json_object("props", "$.k").cast("int")
    return table(spark, d, "events").select(F.col("event_id").alias("id"), F.concat(F.lit("k="), k.cast("string")).alias("items"))


def session_baskets(spark: SparkSession, d: str) -> DataFrame:
    return _items(workloads.session(spark, d))


def semi_join(spark: SparkSession, d: str) -> DataFrame:
    """Orders that have a line of more than 45 pieces."""
    large = table(spark, d, "lineitem").where("l_quantity > 45").select(F.col("l_orderkey").alias("o_orderkey"))
    return table(spark, d, "orders").join(large, "o_orderkey", "left_semi").select("o_orderkey", "o_custkey")


def anti_join(spark: SparkSession, d: str) -> DataFrame:
    """Orders without a line: the empty baskets of the order view."""
    lines = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"))
    return table(spark, d, "orders").join(lines, "o_orderkey", "left_anti").select("o_orderkey", "o_custkey")


def range_join(spark: SparkSession, d: str) -> DataFrame:
    """Purchases of a user within an hour after a click."""
    e = table(spark, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    kinds = [r[0] for r in e.select("event_type").distinct().orderBy("event_type").limit(2).collect()]
    left = e.where(F.col("event_type") == kinds[0]).select(F.col("event_id").alias("a"), "user_id", F.col("t").alias("start"))
    right = e.where(F.col("event_type") == kinds[1]).select(F.col("event_id").alias("b"), "user_id", "t")
    return joins.within(left, right, ["user_id"], "start", "t", 3_600_000_000).select("a", "b")


def asof_events(spark: SparkSession, d: str) -> DataFrame:
    """For each event of the last kind the latest earlier event of the first kind by the same user."""
    e = table(spark, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    kinds = [r[0] for r in e.select("event_type").distinct().orderBy("event_type").collect()]
    left = e.where(F.col("event_type") == kinds[-1]).select("event_id", "user_id", "t")
    right = e.where(F.col("event_type") == kinds[0]).select(F.col("event_id").alias("before_id"), "user_id", "t")
    return joins.as_of(left, right, ["user_id"], "t", ["before_id"]).select("event_id", "before_id")


def cube_flags(spark: SparkSession, d: str) -> DataFrame:
    """A cube over flags of four items: all their fractions and supports in one aggregation."""
    names = ["status=F", "status=O", "region=AFRICA", "region=ASIA"]
    flags = workloads.order_attr(spark, d).select(*[F.array_contains("items", n).cast("int").alias(f"f{i}") for i, n in enumerate(names)])
    cols = [f"f{i}" for i in range(4)]
    return flags.cube(*cols).agg(F.grouping_id().cast("long").alias("gid"), F.count("*").alias("cnt"))


def rollup_dates(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders").select(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"))
    return o.rollup("y", "m").agg(F.count("*").alias("cnt"))


def grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    table(spark, d, "orders").createOrReplaceTempView("sb_orders")
    return spark.sql("SELECT o_orderstatus, o_orderpriority, count(*) AS cnt FROM sb_orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")


def window_rank(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id")
    e = table(spark, d, "events")
    return e.select("event_id", F.row_number().over(w).alias("rn"), F.rank().over(Window.partitionBy("user_id").orderBy("event_type")).alias("rk"), F.dense_rank().over(Window.partitionBy("user_id").orderBy("event_type")).alias("dr"), F.ntile(4).over(w).alias("quarter"))


def window_running(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    o = table(spark, d, "orders")
    run = F.count("*").over(w.rowsBetween(Window.unboundedPreceding, 0))
    return o.select("o_orderkey", run.alias("n_so_far"), F.lag("o_orderkey").over(w).alias("before_key"), F.first("o_orderkey").over(w).alias("first_key"))


def window_range(spark: SparkSession, d: str) -> DataFrame:
    """Orders of a customer within the seven days up to each order."""
    day = F.datediff("o_orderdate", F.lit("1970-01-01").cast("date"))
    o = table(spark, d, "orders").withColumn("day", day)
    return o.select("o_orderkey", F.count("*").over(Window.partitionBy("o_custkey").orderBy("day").rangeBetween(-6, 0)).alias("last_week"))


def topk_per_size(spark: SparkSession, d: str) -> DataFrame:
    """The three most frequent items of each length of name."""
    counts = item_supports(workloads.doc_word(spark, d)).withColumn("size", F.length("item"))
    w = Window.partitionBy("size").orderBy(F.desc("support"), "item")
    return counts.withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("size", "rn", "item", "support")


def set_ops(spark: SparkSession, d: str) -> DataFrame:
    """Customers that bought (intersect), never bought (except), and all rows of both tables (union all), counted."""
    c, o = table(spark, d, "customer").select(F.col("c_custkey").alias("k")), table(spark, d, "orders").select(F.col("o_custkey").alias("k"))
    parts = {"intersect": c.intersect(o), "except": c.exceptAll(o.distinct()), "union_all": c.unionAll(o), "union": c.unionAll(o).distinct(), "intersect_all": o.intersectAll(c)}
    out = None
    for name, df in parts.items():
        row = df.agg(F.lit(name).alias("op"), F.count("*").alias("cnt"))
        out = row if out is None else out.unionByName(row)
    return out


def sample_hash(spark: SparkSession, d: str) -> DataFrame:
    """A repeatable sample: every seventh customer by key."""
    return table(spark, d, "customer").where(F.col("c_custkey") % 7 == 0).select("c_custkey", "c_mktsegment")


def pivot_pairs(spark: SparkSession, d: str) -> DataFrame:
    """Cross table of two attributes, and back to rows."""
    wide = table(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0)
    return wide.unpivot("o_orderpriority", ["F", "O", "P"], "status", "cnt")


def sql_bounds(spark: SparkSession, d: str) -> DataFrame:
    """The rule table and bounds of four flags of lines, from SQL text."""
    from supportbounds.functions import sql

    sql.register(spark)
    table(spark, d, "lineitem").createOrReplaceTempView("sb_lines")
    return spark.sql("""
WITH pattern AS (SELECT CASE WHEN l_quantity >= 10 THEN 1 ELSE 0 END + CASE WHEN l_discount > 0.01 THEN 2 ELSE 0 END + CASE WHEN l_tax > 0.01 THEN 4 ELSE 0 END + CASE WHEN l_returnflag <> 'R' THEN 8 ELSE 0 END AS mask, count(*) AS n FROM sb_lines GROUP BY 1),
supports AS (SELECT id AS term_mask, coalesce(sum(n), 0) AS support FROM range(15) LEFT JOIN pattern ON (mask & id) = id GROUP BY id)
SELECT base_mask, depth, count(*) AS terms, CAST(sum(sign) AS BIGINT) AS signs, CAST(sum(sign * support) AS BIGINT) AS sigma
FROM deduction_rules(4, 4) JOIN supports USING (term_mask) GROUP BY base_mask, depth""")


def salted_join(spark: SparkSession, d: str) -> DataFrame:
    """Lines with the brand of their part, each part's lines spread over several tasks."""
    lines = table(spark, d, "lineitem").select(F.col("l_partkey").alias("k"), "l_orderkey", "l_quantity")
    brands = table(spark, d, "part").select(F.col("p_partkey").alias("k"), "p_brand")
    return joins.salted(lines, brands, ["k"]).groupBy("p_brand").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


def set_similarity_join(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of user-days whose items are alike to 75 per cent, among the days of the first users."""
    days = workloads.userday(spark, d).where(F.split("basket_id", "@")[0].cast("int") < 10)
    return joins.similar_sets(days.select("basket_id", F.array_sort("items").alias("items")), "basket_id", "items", 75)


def lateral_top(spark: SparkSession, d: str) -> DataFrame:
    """The two largest orders of each customer, by a lateral join."""
    customers, orders = table(spark, d, "customer").select("c_custkey").alias("c"), table(spark, d, "orders")
    own = orders.where(F.col("o_custkey") == F.col("c.c_custkey").outer()).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(2).select("o_orderkey")
    return customers.lateralJoin(own)


def quantiles(spark: SparkSession, d: str) -> DataFrame:
    """Exact quartiles of quantities by return flag."""
    parts = [F.percentile("l_quantity", F.lit(q)).alias(f"q{int(100 * q)}") for q in (0.25, 0.5, 0.75)]
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(*parts)


def approximate_distinct(spark: SparkSession, d: str) -> DataFrame:
    """Sketches of the customers of each order status, merged, against the exact count: off by five per cent at most."""
    sketched = table(spark, d, "orders").groupBy("o_orderstatus").agg(F.hll_sketch_agg("o_custkey", F.lit(14)).alias("s"), F.count_distinct("o_custkey").alias("exact"))
    near = F.abs(F.hll_sketch_estimate("s") - F.col("exact")) <= 0.05 * F.col("exact")
    return sketched.select("o_orderstatus", "exact", near.alias("near"))


def observed_rows(spark: SparkSession, d: str) -> DataFrame:
    """Rows and largest total seen while another query ran, without a job of their own."""
    from pyspark.sql import Observation

    seen = Observation("orders")
    watched = table(spark, d, "orders").observe(seen, F.count("*").alias("n"), F.max("o_totalprice").alias("largest"))
    watched.groupBy("o_orderstatus").count().write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(seen.get["n"], seen.get["largest"])], "n long, largest double")


def window_share(spark: SparkSession, d: str) -> DataFrame:
    """The share of each priority in the orders of its status."""
    counts = table(spark, d, "orders").groupBy("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))
    share = F.col("n") / F.sum("n").over(Window.partitionBy("o_orderstatus"))
    return counts.select("o_orderstatus", "o_orderpriority", F.round(share, 9).alias("share"))


def window_more(spark: SparkSession, d: str) -> DataFrame:
    """Relative ranks, and values of neighbouring and third rows."""
    w = Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, d, "events").select(
        "event_id", F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"), F.lead("event_id", 1).over(w).alias("next_id"),
        F.nth_value("event_id", 3).over(whole).alias("third_id"), F.last("event_id").over(whole).alias("last_id"),
    )


def bit_aggregates(spark: SparkSession, d: str) -> DataFrame:
    key = F.col("o_custkey")
    return table(spark, d, "orders").groupBy("o_orderstatus").agg(F.bit_and(key).alias("all_bits"), F.bit_or(key).alias("some_bits"), F.bit_xor(key).alias("odd_bits"))


def sort_offset(spark: SparkSession, d: str) -> DataFrame:
    """The 11th to 30th customers by balance, nulls last."""
    ordered = table(spark, d, "customer").orderBy(F.desc_nulls_last("c_acctbal"), "c_custkey")
    return ordered.offset(10).limit(20).select("c_custkey", "c_acctbal")


def hash_keys(spark: SparkSession, d: str) -> DataFrame:
    """A stable sample by the digest of a key: one row in sixteen."""
    digest = F.md5(F.col("c_custkey").cast("string").cast("binary"))
    return table(spark, d, "customer").where(F.substring(digest, 1, 1) == "0").select("c_custkey", digest.alias("digest"))


def time_window_baskets(spark: SparkSession, d: str) -> DataFrame:
    """Kinds of events of each user in windows of six hours."""
    hours = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 21_600_000_000)
    return table(spark, d, "events").groupBy("user_id", hours.alias("slot")).agg(F.array_join(F.array_sort(F.collect_set("event_type")), " ").alias("items"))


QUERIES: dict[str, Query] = {
    f.__name__: f
    for f in (
        basket_lines_per_order, attr_items, word_items, json_items, session_baskets, semi_join, anti_join, range_join, asof_events, cube_flags, rollup_dates, grouping_sets, window_rank, window_running,
        window_range, topk_per_size, set_ops, sample_hash, pivot_pairs, sql_bounds, salted_join, set_similarity_join, lateral_top, quantiles, approximate_distinct, observed_rows, window_share, window_more,
        bit_aggregates, sort_offset, hash_keys, time_window_baskets,
    )
}

_WORDS = r"SELECT DISTINCT doc_id, unnest(string_split_regex(lower(coalesce(text, '')), '[^\p{L}\p{N}]+')) AS item FROM documents"
_ATTR = """SELECT o_orderkey AS id, unnest(['status=' || o_orderstatus, 'priority=' || o_orderpriority, 'segment=' || c_mktsegment, 'region=' || r_name, 'nation=' || n_name,
 'price=' || CAST(least(4, floor(o_totalprice / 100000)) AS INT)]) AS item FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"""
ORACLES: dict[str, str] = {
    "basket_lines_per_order": "SELECT l_orderkey AS id, count(*) AS n_lines, count(DISTINCT l_partkey) AS n_items FROM lineitem GROUP BY 1",
    "attr_items": f"SELECT id, string_agg(item, ' ' ORDER BY item) AS items FROM ({_ATTR}) GROUP BY id",
    "word_items": f"SELECT d.doc_id AS id, CAST(count(item) AS INT) AS n_items FROM documents d LEFT JOIN (SELECT * FROM ({_WORDS}) WHERE item <> '') w USING (doc_id) GROUP BY 1",
    "json_items": """SELECT event_id AS id, 'k=' || CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS INT) AS items FROM events""",
    "session_baskets": """WITH e AS (SELECT user_id, ts, unnest([event_type, 'k' || (CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS INT) // 10)]) AS item FROM events),
g AS (SELECT *, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 21600000000 THEN 0 ELSE 1 END AS new FROM e),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS session FROM g)
SELECT user_id || '@' || session AS id, string_agg(DISTINCT item, ' ' ORDER BY item) AS items FROM s GROUP BY 1""",
    "semi_join": "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45)",
    "anti_join": "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)",
    "range_join": """WITH k AS (SELECT DISTINCT event_type FROM events ORDER BY 1 LIMIT 2)
SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND epoch_us(b.ts) - epoch_us(a.ts) BETWEEN 0 AND 3600000000
WHERE a.event_type = (SELECT min(event_type) FROM k) AND b.event_type = (SELECT max(event_type) FROM k)""",
    "asof_events": """WITH r AS (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = (SELECT min(event_type) FROM events) GROUP BY 1, 2)
SELECT l.event_id, r.event_id AS before_id FROM (SELECT * FROM events WHERE event_type = (SELECT max(event_type) FROM events)) l ASOF LEFT JOIN r ON l.user_id = r.user_id AND l.ts >= r.ts""",
    "cube_flags": f"""WITH f AS (SELECT id, CAST(bool_or(item = 'status=F') AS INT) AS f0, CAST(bool_or(item = 'status=O') AS INT) AS f1, CAST(bool_or(item = 'region=AFRICA') AS INT) AS f2, CAST(bool_or(item = 'region=ASIA') AS INT) AS f3 FROM ({_ATTR}) GROUP BY id)
SELECT f0, f1, f2, f3, CAST(grouping_id(f0, f1, f2, f3) AS BIGINT) AS gid, count(*) AS cnt FROM f GROUP BY CUBE (f0, f1, f2, f3)""",
    "rollup_dates": "SELECT CAST(y AS INT) AS y, CAST(m AS INT) AS m, count(*) AS cnt FROM (SELECT year(o_orderdate) AS y, month(o_orderdate) AS m FROM orders) GROUP BY ROLLUP (y, m)",
    "grouping_sets": "SELECT o_orderstatus, o_orderpriority, count(*) AS cnt FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())",
    "window_rank": """SELECT event_id, CAST(row_number() OVER w AS INT) AS rn, CAST(rank() OVER t AS INT) AS rk, CAST(dense_rank() OVER t AS INT) AS dr, CAST(ntile(4) OVER w AS INT) AS quarter
FROM events WINDOW w AS (PARTITION BY user_id ORDER BY value DESC, event_id), t AS (PARTITION BY user_id ORDER BY event_type)""",
    "window_running": """SELECT o_orderkey, count(*) OVER (w ROWS UNBOUNDED PRECEDING) AS n_so_far, lag(o_orderkey) OVER w AS before_key, first_value(o_orderkey) OVER w AS first_key
FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)""",
    "window_range": "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY date_diff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE)) RANGE BETWEEN 6 PRECEDING AND CURRENT ROW) AS last_week FROM orders",
    "topk_per_size": f"""SELECT CAST(size AS INT) AS size, CAST(rn AS INT) AS rn, item, support FROM (SELECT length(item) AS size, item, count(*) AS support, row_number() OVER (PARTITION BY length(item) ORDER BY count(*) DESC, item) AS rn
FROM ({_WORDS}) WHERE item <> '' GROUP BY item) WHERE rn <= 3""",
    "set_ops": """SELECT 'intersect' AS op, count(*) AS cnt FROM (SELECT c_custkey FROM customer INTERSECT SELECT o_custkey FROM orders)
UNION ALL SELECT 'except', count(*) FROM (SELECT c_custkey FROM customer EXCEPT SELECT o_custkey FROM orders)
UNION ALL SELECT 'union_all', count(*) FROM (SELECT c_custkey FROM customer UNION ALL SELECT o_custkey FROM orders)
UNION ALL SELECT 'union', count(*) FROM (SELECT c_custkey FROM customer UNION SELECT o_custkey FROM orders)
UNION ALL SELECT 'intersect_all', count(*) FROM (SELECT o_custkey FROM orders INTERSECT ALL SELECT c_custkey FROM customer)""",
    "sample_hash": "SELECT c_custkey, c_mktsegment FROM customer WHERE c_custkey % 7 = 0",
    "pivot_pairs": "SELECT p AS o_orderpriority, s AS status, count(o_orderkey) AS cnt FROM (SELECT DISTINCT o_orderpriority AS p FROM orders) CROSS JOIN (VALUES ('F'), ('O'), ('P')) x(s) LEFT JOIN orders ON o_orderpriority = p AND o_orderstatus = s GROUP BY ALL",
    "sql_bounds": """WITH p AS (SELECT coalesce(CAST(l_quantity >= 10 AS INT), 0) + 2 * coalesce(CAST(l_discount > 0.01 AS INT), 0) + 4 * coalesce(CAST(l_tax > 0.01 AS INT), 0) + 8 * coalesce(CAST(l_returnflag <> 'R' AS INT), 0) AS m FROM lineitem),
s AS (SELECT t, (SELECT count(*) FROM p WHERE (m & t) = t) AS s FROM (SELECT range AS t FROM range(15)))
SELECT b AS base_mask, CAST(4 - bit_count(b) AS INT) AS depth, count(*) AS terms, CAST(sum(CASE WHEN (4 - bit_count(t)) % 2 = 1 THEN 1 ELSE -1 END) AS BIGINT) AS signs,
 CAST(sum(CASE WHEN (4 - bit_count(t)) % 2 = 1 THEN s ELSE -s END) AS BIGINT) AS sigma FROM (SELECT range AS b FROM range(15)) JOIN s ON (t & b) = b GROUP BY ALL""",
    "salted_join": "SELECT p_brand, count(*) AS n, sum(l_quantity) AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1",
    "set_similarity_join": """WITH i AS (SELECT DISTINCT user_id || '@' || strftime(ts, '%Y-%m-%d') AS b, unnest([event_type, 'k' || (CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS INT) // 10)]) AS item FROM events WHERE user_id < 10),
n AS (SELECT b, count(*) AS n FROM i GROUP BY b), p AS (SELECT x.b AS a, y.b AS b, count(*) AS shared FROM i x JOIN i y ON x.item = y.item AND x.b < y.b GROUP BY ALL)
SELECT a, p.b, CAST(shared AS INT) AS shared FROM p JOIN n x ON x.b = a JOIN n y ON y.b = p.b WHERE 100 * shared >= 75 * (x.n + y.n - shared)""",
    "lateral_top": "SELECT o_custkey AS c_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders JOIN customer ON c_custkey = o_custkey) WHERE r <= 2",
    "quantiles": "SELECT l_returnflag, quantile_cont(l_quantity, 0.25) AS q25, quantile_cont(l_quantity, 0.5) AS q50, quantile_cont(l_quantity, 0.75) AS q75 FROM lineitem GROUP BY 1",
    "approximate_distinct": "SELECT o_orderstatus, count(DISTINCT o_custkey) AS exact, true AS near FROM orders GROUP BY 1",
    "observed_rows": "SELECT count(*) AS n, max(o_totalprice) AS largest FROM orders",
    "window_share": "SELECT o_orderstatus, o_orderpriority, round(n / sum(n) OVER (PARTITION BY o_orderstatus), 9) AS share FROM (SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ALL)",
    "window_more": """SELECT event_id, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd, lead(event_id) OVER w AS next_id, nth_value(event_id, 3) OVER f AS third_id, last_value(event_id) OVER f AS last_id
FROM events WINDOW w AS (PARTITION BY user_id ORDER BY value DESC, event_id), f AS (PARTITION BY user_id ORDER BY value DESC, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""",
    "bit_aggregates": "SELECT o_orderstatus, bit_and(o_custkey) AS all_bits, bit_or(o_custkey) AS some_bits, bit_xor(o_custkey) AS odd_bits FROM orders GROUP BY 1",
    "sort_offset": "SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC NULLS LAST, c_custkey LIMIT 20 OFFSET 10",
    "hash_keys": "SELECT c_custkey, md5(CAST(c_custkey AS VARCHAR)) AS digest FROM customer WHERE md5(CAST(c_custkey AS VARCHAR))[1] = '0'",
    "time_window_baskets": "SELECT user_id, CAST(floor(epoch_us(ts) / 21600000000) AS BIGINT) AS slot, string_agg(DISTINCT event_type, ' ' ORDER BY event_type) AS items FROM events GROUP BY 1, 2",
}
