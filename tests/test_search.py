"""Searches in tiles, and exact pairs by rare elements, against all pairs."""

from pyspark.sql import functions as F

from wsig.operators import bags as B
from wsig.operators import lsh
from wsig.operators.bags import wjaccard_all_pairs


def _bags(spark):
    rows = spark.range(3000).select((F.col("id") % 300).alias("bag_id"), (F.xxhash64("id") % 12).alias("elem"), (F.col("id") % 7 + 1.0).alias("weight"))
    return B.aggregate_bags(rows)


def test_search_is_all_pairs_of_the_queries(spark, monkeypatch):
    monkeypatch.setattr(lsh, "QUERY_BLOCK", 7)
    monkeypatch.setattr(lsh, "BAG_BLOCK", 50)
    bags = lsh.settle(_bags(spark))
    pairs = {(r.a, r.b): r.j for r in wjaccard_all_pairs(bags).collect()}
    want = {(x, y): j for (a, b), j in pairs.items() for x, y in ((a, b), (b, a)) if x % 10 == 0}
    got = lsh.search(bags, F.col("bag_id") % 10 == 0)
    assert "Join" not in got._jdf.queryExecution().executedPlan().toString()
    assert {(r.a, r.b): round(r.j, 9) for r in got.collect()} == {k: round(j, 9) for k, j in want.items()}
    near = lsh.nearest(lsh.search(bags, F.col("bag_id") % 10 == 0, 2).withColumn("j", F.round("j", 9)), 2).collect()
    for q in {a for a, _ in want}:
        best = sorted(((-round(j, 9), b) for (a, b), j in want.items() if a == q))[:2]
        assert sorted((r.rank, r.neighbour) for r in near if r["query"] == q) == [(i + 1, b) for i, (_, b) in enumerate(best)]
