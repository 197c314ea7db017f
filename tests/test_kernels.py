"""Kernels on batches of many bags against the same on one bag at a time."""

import numpy as np
from pyspark.sql import functions as F

from wsig.functions.prng import U1, U2, np_u01
from wsig.operators import baselines


def _bags(n=40):
    rng = np.random.default_rng(5)
    return {k: (rng.integers(0, 10**6, size).astype(np.int64), rng.integers(1, 60, size) + rng.random(size)) for k, size in enumerate(rng.integers(1, 30, n).tolist())}


def _flat(bags):
    bag = np.concatenate([np.full(len(e), k) for k, (e, _) in bags.items()])
    return bag, np.concatenate([e for e, _ in bags.values()]), np.concatenate([w for _, w in bags.values()])


def _kernels(m):
    return {
        "cws": lambda b, e, w, n: baselines._least_in_bags(b, e, w, n, m, lambda e, w: baselines.cws_points(e, w, m)),
        "permuted": lambda b, e, w, n: baselines._least_in_bags(b, e, w, n, m, lambda e, w: baselines.permuted_points(e, m)),
        "rounds": lambda b, e, w, n: baselines.round_sketches(b, e, n, m),
    }


def test_bags_together_and_in_chunks_give_what_each_gives_alone(monkeypatch):
    bags = _bags()
    for kernel in _kernels(6).values():
        monkeypatch.setattr(baselines, "CELLS", 1 << 18)
        alone = [kernel(np.zeros(len(e), np.int64), e, w, 1) for e, w in bags.values()]
        monkeypatch.setattr(baselines, "CELLS", 30)  # five elements at a time
        ids, h = kernel(*_flat(bags), len(bags))
        assert (ids == np.concatenate([a[0] for a in alone])).all() and (h == np.concatenate([a[1] for a in alone])).all()


def test_rounds_and_order_by_definition():
    m, (elem, _) = 6, _bags()[3]
    ids, h = baselines.round_sketches(np.zeros(len(elem), np.int64), elem, 1, m)
    for b in range(m):
        values = [(i + np_u01(0, e, i, U1), e) for e in elem for i in range(2 * m) if (int(np_u01(0, e, i, U2) * m) == b if i < m else i - m == b)]
        assert (h[0, b], ids[0, b]) == min(values)


def test_whole_bags_across_batches(spark):
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        bags = _bags()
        bag, elem, weight = _flat(bags)
        rows = spark.createDataFrame(list(zip(bag.tolist(), elem.tolist(), weight.tolist())), "bag_id long, elem long, weight double")
        got = {(r.bag_id, r.j): (r.id, r.h) for r in baselines.sig_cws(rows, 6).collect()}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    ids, h = _kernels(6)["cws"](bag, elem, weight, len(bags))
    assert got == {(k, j): (ids[k, j], h[k, j]) for k in bags for j in range(6)}


def test_points_on_the_line_are_not_broadcast(spark):
    line = baselines.universe_line(spark.range(1000).select(F.col("id").alias("elem"), (F.col("id") % 5 + 1.0).alias("bound")))
    points = spark.range(2000).select((F.col("id") % 8).cast("int").alias("j"), F.col("id").cast("int").alias("k"), (F.col("id") * 1.5).alias("at"))
    placed = baselines.place_on_line(points, line, 3000.0, 1000)
    assert "SortMergeJoin [cell" in placed._jdf.queryExecution().executedPlan().toString()
    got, want = placed.collect(), {r.elem: (r.start, r.end) for r in line.collect()}
    assert len(got) == 2000 and all(want[r.elem][0] <= r.k * 1.5 < want[r.elem][1] for r in got)
