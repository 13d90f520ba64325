"""Joins against what Spark's own give."""

from supportbounds.operators import joins


def test_copies_of_a_salted_join_are_not_broadcast(spark, capsys):
    left = spark.range(2000).selectExpr("CAST(id % 7 AS INT) AS k", "id AS v")
    right = spark.range(5).selectExpr("CAST(id AS INT) AS k", "concat('b', id) AS name")
    got = joins.salted(left, right, ["k"])
    got.explain()
    assert "BroadcastHashJoin" not in capsys.readouterr().out
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, left.join(right, "k").collect()))
    outer = joins.salted(left, right, ["k"], how="left")
    assert sorted(map(tuple, outer.collect()), key=repr) == sorted(map(tuple, left.join(right, "k", "left").collect()), key=repr)
