"""Basket views over the given tables, one for each role that the experiments need."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from supportbounds.operators import baskets as b
from supportbounds.sources.tables import table

#: Items of the functional-dependency view: three nations of one region, all regions, two of the three states.
FD_ITEMS = ["status=F", "status=O", "region=AFRICA", "nation=NATION_0", "nation=NATION_5", "nation=NATION_10"]


def order_part(spark: SparkSession, d: str) -> DataFrame:
    """Sparse: the parts of an order."""
    return b.from_groups(table(spark, d, "lineitem"), "l_orderkey", "l_partkey")


def order_brand(spark: SparkSession, d: str) -> DataFrame:
    """Sparse, few items: the brands of an order."""
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_partkey")
    return b.from_groups(lines.join(table(spark, d, "part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey")), "l_orderkey", "p_brand")


def _event_items(spark: SparkSession, d: str) -> DataFrame:
    k = F.concat(F.lit("k"), F.floor(F.get_json_object("props", "$.k").cast("int") / 10).cast("string"))
    return table(spark, d, "events").select("user_id", "ts", F.explode(F.array("event_type", k)).alias("item"))


def userday(spark: SparkSession, d: str) -> DataFrame:
    """Clicks: what a user did on one day."""
    key = F.concat_ws("@", F.col("user_id"), F.date_format("ts", "yyyy-MM-dd"))
    return b.from_groups(_event_items(spark, d), key, "item")


def session(spark: SparkSession, d: str, gap_seconds: int = 21600) -> DataFrame:
    """Clicks: what a user did without a pause of the given length."""
    rows = _event_items(spark, d)
    w = Window.partitionBy("user_id").orderBy("ts")
    new = F.when(F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lag("ts").over(w).cast("timestamp")) < gap_seconds * 1_000_000, 0).otherwise(1)
    numbered = rows.withColumn("new", new).withColumn("session", F.sum("new").over(w.rangeBetween(Window.unboundedPreceding, 0)))
    return b.from_groups(numbered, F.concat_ws("@", "user_id", "session"), "item")


def _orders_wide(spark: SparkSession, d: str) -> DataFrame:
    customers = table(spark, d, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    places = table(spark, d, "nation").join(F.broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    buyers = customers.join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey"))
    return table(spark, d, "orders").join(buyers, F.col("o_custkey") == F.col("c_custkey"))


def order_attr(spark: SparkSession, d: str) -> DataFrame:
    """Attribute-value pairs of an order."""
    band = F.least(F.lit(4), F.floor(F.col("o_totalprice") / 100000)).cast("int")
    columns = {"status": F.col("o_orderstatus"), "priority": F.col("o_orderpriority"), "segment": F.col("c_mktsegment"), "region": F.col("r_name"), "nation": F.col("n_name"), "price": band}
    return b.from_columns(_orders_wide(spark, d), "o_orderkey", columns)


def order_fd(spark: SparkSession, d: str) -> DataFrame:
    """A functional dependency: three nations that lie in one region, with region and status."""
    nation = F.when(F.col("n_name").isin("NATION_0", "NATION_5", "NATION_10"), F.col("n_name"))
    return b.from_columns(_orders_wide(spark, d), "o_orderkey", {"status": F.col("o_orderstatus"), "region": F.col("r_name"), "nation": nation})


def line_attr(spark: SparkSession, d: str) -> DataFrame:
    """Attribute-value pairs of a line; a line has no key, so each row is a basket of its own."""
    lines = table(spark, d, "lineitem").join(table(spark, d, "part").select("p_partkey", "p_brand", "p_type"), F.col("l_partkey") == F.col("p_partkey"))
    columns = {
        "flag": F.col("l_returnflag"), "state": F.col("l_linestatus"), "tax": F.round(F.col("l_tax") * 100).cast("int"), "discount": F.round(F.col("l_discount") * 100).cast("int"),
        "quantity": F.floor(F.col("l_quantity") / 10).cast("int"), "brand": F.col("p_brand"), "type": F.col("p_type"), "year": F.year("l_shipdate"),
    }
    return b.from_columns(lines, F.monotonically_increasing_id(), columns)


def doc_word(spark: SparkSession, d: str) -> DataFrame:
    """Dense and correlated: the words of a document."""
    return b.from_text(table(spark, d, "documents"), "doc_id", "text")


def doc_line(spark: SparkSession, d: str) -> DataFrame:
    return b.from_lines(table(spark, d, "documents"), "doc_id", "text")


def conv_word(spark: SparkSession, d: str) -> DataFrame:
    words = b.from_text(table(spark, d, "conversations"), "conv_id", "text")
    return b.from_groups(words.select("basket_id", F.explode("items").alias("item")), "basket_id", "item")


def page_tag(spark: SparkSession, d: str) -> DataFrame:
    tags = F.array_distinct(F.regexp_extract_all(F.lower("html"), F.lit(r"<([a-z][a-z0-9]*)"), F.lit(1)))
    return table(spark, d, "pages").select(F.col("page_id").alias("basket_id"), F.coalesce(tags, F.array().cast("array<string>")).alias("items"))


def doc_label(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "documents").select("doc_id", "lang", "source").join(table(spark, d, "labels"), "doc_id")
    return b.from_columns(rows, "doc_id", {c: F.col(c) for c in ("lang", "source", "quality", "toxic")})


def vec_sign(spark: SparkSession, d: str) -> DataFrame:
    return b.from_vector_signs(table(spark, d, "embeddings"), "vec_id", "embedding")


def doc_bench(spark: SparkSession, d: str) -> DataFrame:
    """Words of documents that the benchmark has too."""
    known = b.from_text(table(spark, d, "benchmark"), "item_id", "text").select(F.explode("items").alias("item")).distinct()
    docs = table(spark, d, "documents")
    words = b.from_text(docs, "doc_id", "text").select("basket_id", F.explode("items").alias("item")).join(known, "item", "left_semi")
    return b.with_empty(words.groupBy("basket_id").agg(F.collect_list("item").alias("items")), docs, "doc_id")


def supplier_nation(spark: SparkSession, d: str) -> DataFrame:
    """Nations and regions of an order's suppliers: a dependency inside a group."""
    places = table(spark, d, "nation").join(F.broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    suppliers = table(spark, d, "supplier").join(F.broadcast(places), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name", "r_name")
    rows = table(spark, d, "lineitem").select("l_orderkey", "l_suppkey").join(suppliers, F.col("l_suppkey") == F.col("s_suppkey"))
    return b.from_groups(rows.select("l_orderkey", F.explode(F.array("n_name", "r_name")).alias("item")), "l_orderkey", "item")


VIEWS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (order_part, order_brand, userday, session, order_attr, order_fd, line_attr, doc_word, doc_line, conv_word, page_tag, doc_label, vec_sign, doc_bench, supplier_nation)
}


def worked_example(spark: SparkSession) -> DataFrame:
    """The ten baskets of the worked example."""
    rows = ["A B C", "A C D", "A B D", "C D", "B C D", "A D", "B D", "B C D", "B C D", "A B C D"]
    return spark.createDataFrame([(i, r.split()) for i, r in enumerate(rows)], "basket_id int, items array<string>")
