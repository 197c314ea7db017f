"""Bags as rows (bag_id, items) against bags as rows of elements."""

import numpy as np
import pytest

from wsig.functions.ladder import BinaryLadder, IntegerLadder
from wsig.operators import bag_kernel, lp_kernel, lsh, poisson, prefix
from wsig.operators import bags as B


@pytest.mark.parametrize("unit,weight,ladder", [("word", "tf", IntegerLadder(8)), ("shingle", "binary", BinaryLadder())])
def test_whole_bags_are_the_same(spark, unit, weight, ladder):
    """Also of texts that share an id; their signatures and classes as well."""
    rng = np.random.default_rng(3)
    texts = [" ".join(f"w{x}" for x in rng.integers(0, 30, n)) for n in rng.integers(0, 20, 30)]
    rows = [(i, t) for i, t in enumerate(texts)] + [(100 + i, t) for i, t in enumerate(texts[:9])] + [(3, texts[4]), (200, None), (201, "..."), (None, "a b")]
    for part in (rows, rows[:39]):
        docs = spark.createDataFrame(part, "doc_id long, text string").repartition(3)
        long = lsh.settle(B.bag_from_text(docs, "doc_id", "text", unit, 5, weight).where("bag_id is not null"))
        whole = lsh.settle(B.whole_bags_from_text(docs, "doc_id", "text", unit, 5, weight))
        assert sorted(map(tuple, B.unnest(whole).collect())) == sorted(map(tuple, long.collect()))
        assert sorted(map(tuple, lsh.equal_bags(whole).collect())) == sorted(map(tuple, lsh.equal_bags(long).collect()))
        want = {r.bag_id: r.sig for r in poisson.assemble(lp_kernel.sig_lp_arrow(long, 16, ladder), 16).collect()}
        assert {r.bag_id: r.sig for r in bag_kernel.sig_items(whole, 16, ladder).collect()} == want
        ids = spark.createDataFrame([(3,), (101,), (-5,)], "bag_id long")
        kept = lambda keep: {r.bag_id for r in B.only(whole, ids, keep).collect()}
        assert kept(True) == want.keys() & {3, 101} and kept(False) == want.keys() - {3, 101}


def test_elements_are_not_shuffled(spark):
    """Only buckets of four bytes and the first elements of bags are, whatever the bags hold."""
    docs = spark.createDataFrame([(i, " ".join(f"w{i * j % 50}" for j in range(30))) for i in range(40)], "doc_id long, text string")
    whole = B.whole_bags_from_text(docs, "doc_id", "text", "shingle", 5, "binary")
    for plan in (whole, bag_kernel.sig_items(whole, 16, BinaryLadder()), prefix.heads(whole, 0.8)):
        assert "Exchange" not in plan._jdf.queryExecution().executedPlan().toString()


def test_frequent_elements_come_last(spark, monkeypatch):
    monkeypatch.setattr(prefix, "FREQUENT", 5)
    bags = B.nest(spark.createDataFrame([(b, e, 1.0) for b in range(20) for e in (7, 1000 + b, 2000 + b, 3000 + b)], "bag_id long, elem long, weight double"))
    buckets, often = prefix.frequent(bags)
    assert buckets.tolist() == prefix._bucket(np.array([7])).tolist() and often.tolist() == [20]
    assert 7 not in {r.block for r in prefix.heads(bags, 0.8).collect()}
