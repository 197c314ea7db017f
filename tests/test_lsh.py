"""Joins on buckets that hold more bags than a block, against exact similarities of all pairs."""

import numpy as np

from wsig.functions import estimate as E
from wsig.functions.ladder import FloatLadder
from wsig.operators import lp_kernel, lsh, poisson
from wsig.operators.bags import wjaccard_all_pairs


def large_bucket(spark):
    """90 different bags around a common core (pairs from 0.77 to 0.9), 5 times each the first ten."""
    rng = np.random.default_rng(4)
    bags = [set(range(60)) | set(rng.choice(np.arange(100, 106), 2, replace=False).tolist()) | set(rng.choice(np.arange(200, 100_000), n, replace=False).tolist()) for n in rng.integers(1, 9, 90)]
    bags += bags[:10] * 4
    return lsh.settle(spark.createDataFrame([(i, int(e), 1.0) for i, b in enumerate(bags) for e in b], "bag_id long, elem long, weight double"))


def signatures(bags, m=64):
    return lsh.settle(poisson.assemble(lp_kernel.sig_lp_arrow(bags, m, FloatLadder(32)), m))


def test_large_buckets_lose_no_pair(spark, monkeypatch):
    monkeypatch.setattr(lsh, "BLOCK", 20)
    bags = large_bucket(spark)
    one = spark.createDataFrame([(i, [7] * 64) for i in range(130)], "bag_id long, sig array<long>")  # all in one bucket
    got = {(r.a, r.b): r.j for r in lsh.similarity_join(bags, one, 64, 0.8).collect()}
    want = {(r.a, r.b): r.j for r in wjaccard_all_pairs(bags).where("j >= 0.8").collect()}
    assert len(want) > 3000 and got.keys() == want.keys()
    assert all(abs(got[k] - want[k]) < 1e-12 for k in want)
    nodes = bags.select(bags.bag_id.alias("node")).distinct()
    clusters = lambda edges: sorted(tuple(r) for r in lsh.components(nodes, edges).collect())
    pairs = spark.createDataFrame(list(want), "a long, b long")
    assert clusters(lsh.similarity_links(bags, one, 64, 0.8)) == clusters(pairs)


def test_candidates_of_a_large_bucket_are_all_pairs(spark, monkeypatch):
    monkeypatch.setattr(lsh, "BLOCK", 16)
    keys = spark.createDataFrame([(i, band, 5) for i in range(100) for band in (0, 1)], "bag_id long, band int, bucket long")
    rows = lsh.candidate_pairs(keys).collect()
    assert {(r.a, r.b) for r in rows} == {(a, b) for a in range(100) for b in range(a + 1, 100)} and len(rows) == 4950


def test_pairs_at_the_threshold_are_found(spark):
    """400 pairs of similarity 0.80 and 0.85."""
    rows = [(2 * i + k, i * 1000 + e, 1.0) for i in range(400) for k in (0, 1) for e in [*range(80 + 5 * (i % 2)), *range(100 + 50 * k, 110 + 50 * k - 2 * (i % 2))]]
    bags = lsh.settle(spark.createDataFrame(rows, "bag_id long, elem long, weight double"))
    want = {(r.a, r.b) for r in wjaccard_all_pairs(bags).where("j >= 0.8").collect()}
    got = {(r.a, r.b) for r in lsh.similarity_join(bags, signatures(bags), 64, 0.8).collect()}
    assert len(want) == 400 and got <= want and len(got) >= 0.99 * len(want)


def test_bands_keep_the_recall_asked_for():
    for m, tau, recall in ((64, 0.8, 0.999), (64, 0.9, 0.999), (128, 0.5, 0.99), (16, 0.8, 0.9)):
        bands, rows = E.bands_for_recall(m, tau, recall)
        assert bands * rows <= m and E.collision_probability(tau, bands, rows) >= recall
