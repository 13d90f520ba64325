"""Queries against DuckDB over the same small tables."""

import math
import os

import duckdb
import pytest

import __spark_entry__ as entry_points
from supportbounds import oracles, queries, relational
from supportbounds.sources.tables import TABLES, read_transactions, write_transactions
from supportbounds.streaming import streams

SF = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")
#: Fast ones; the driver compares all of them.
CHOSEN = [
    "worked_example_rules", "worked_example_bounds", "item_supports", "pair_supports", "fractions_3", "cover_identity", "sigma_rules_depth2", "interval_bounds_depth2", "count_trie", "count_bitmap", "pattern_weights",
    *relational.ORACLES, *streams.ORACLES,
]


def rows_of(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])

    def plain(v):
        if isinstance(v, bool) or v is None or isinstance(v, str):
            return v
        return None if isinstance(v, float) and math.isnan(v) else round(float(v), 6)

    return sorted(columns), sorted((tuple(plain(r[i]) for i in order) for r in rows), key=repr)


def same(spark, query, sql, sf_dir=SF):
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    df = query(spark, sf_dir)
    found = con.execute(sql)
    want = rows_of([d[0] for d in found.description], found.fetchall())
    assert rows_of(df.columns, df.collect()) == want


@pytest.mark.parametrize("name", CHOSEN)
def test_same_as_duckdb(spark, name):
    every = {**queries.QUERIES, **relational.QUERIES, **streams.QUERIES}
    sql = {**oracles.all_oracles(), **relational.ORACLES, **streams.ORACLES}
    same(spark, every[name], sql[name])


def test_every_oracle_has_a_query():
    assert set(entry_points.oracle_sql()) <= set(entry_points.queries())


def test_entry(spark):
    assert {"items", "support", "lower", "upper"} <= set(entry_points.entry(spark).columns)


def test_transaction_files(spark, tmp_path):
    df = spark.createDataFrame([(0, ["a", "b"]), (1, []), (2, ["c"])], "basket_id int, items array<string>")
    write_transactions(df, str(tmp_path / "t"))
    assert sorted(r["items"] for r in read_transactions(spark, str(tmp_path / "t")).collect()) == [[], ["a", "b"], ["c"]]


def test_dictionary_is_broadcast_and_rules_have_no_cartesian_product(spark, capsys):
    db = queries.words(spark, SF)
    run = queries.mine_nonderivable(db, 60)
    run.sets.explain()
    assert "CartesianProduct" not in capsys.readouterr().out
