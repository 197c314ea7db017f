"""Draws of the heap walks, one at a time, against numpy's; bags that span batches."""

import numpy as np

from wsig.functions.ladder import IntegerLadder
from wsig.functions.prng import np_hash, np_u01
from wsig.operators import lp_kernel


def test_single_draws_are_numpys():
    walk = lp_kernel.Walker(8, IntegerLadder(64), lp_kernel.Work(), 3)
    for keys in ((5, 0, 64, 1), (-(10**17), 7, 8, 4, 2), (2**62, 1)):
        assert walk._draw(*keys) == float(np_u01(3, *keys)) and walk._draw(*keys) == float(np_u01(3, *keys))
        assert lp_kernel.one_hash(42, 3, *keys) == int(np_hash(3, *keys))
    assert walk.work.draws == 6


def test_walks_of_bags_across_batches(spark):
    rng = np.random.default_rng(2)
    bags = {k: list(zip(rng.integers(0, 10**6, n).tolist(), rng.integers(1, 60, n).astype(float).tolist())) for k, n in enumerate(rng.integers(1, 20, 12).tolist())}
    rows = spark.createDataFrame([(k, e, w) for k, items in bags.items() for e, w in items], "bag_id long, elem long, weight double")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "6")
    try:
        got = {r.bag_id: r for r in lp_kernel.lp_costs(rows, 8, IntegerLadder(64), "one_pass", "weight_desc").collect()}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    for k, items in bags.items():
        sig = lp_kernel.one_pass(sorted(items, key=lambda x: (-x[1], x[0])), 8, IntegerLadder(64))
        assert got[k].n == len(items) and {c: got[k][c] for c in sig.work.as_dict(sig.tracker)} == sig.work.as_dict(sig.tracker)
