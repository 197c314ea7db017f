import numpy as np
import pytest
from pyspark.sql import functions as F

from wsig.functions.estimate import expected_points
from wsig.functions.ladder import BinaryLadder, FloatLadder, GeometricLadder, IntegerLadder
from wsig.functions.prng import Prng
from wsig.operators import bags as B
from wsig.operators import baselines, lp_kernel, lsh, poisson
from wsig.plans import verify
from wsig.schema import check_bag
from wsig.sources import io

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def bags(spark):
    rng = np.random.default_rng(3)
    rows = [(b, int(e), float(w)) for b, n in enumerate((1, 2, 5, 40, 150)) for e, w in zip(rng.integers(0, 10**6, n), 1 + rng.exponential(8, n))]
    return spark.createDataFrame(rows, "bag_id long, elem long, weight double").groupBy("bag_id", "elem").agg(F.max("weight").alias("weight")).cache()


def cells(df):
    return {(r.bag_id, r.j): (r.id, r.h) for r in df.collect()}


def same(a, b):
    assert a.keys() == b.keys()
    assert all(a[k][0] == b[k][0] and abs(a[k][1] - b[k][1]) <= 1e-12 * a[k][1] for k in a)


@pytest.mark.parametrize("ladder", [IntegerLadder(64), GeometricLadder(1.0, 0.1, 100.0), BinaryLadder()])
def test_every_engine_finds_the_same_points(bags, ladder):
    want = cells(lp_kernel.sig_lp_heap(bags, 8, ladder, "one_pass"))
    assert want == cells(lp_kernel.sig_lp_heap(bags, 8, ladder, "two_phase"))
    same(want, cells(lp_kernel.sig_lp_arrow(bags, 8, ladder)))
    same(want, cells(poisson.sig_lp(bags, 8, ladder, Prng())))
    assert len(want) == 5 * 8


def test_float_levels_and_flags_change_no_value(bags):
    f = FloatLadder(32)
    want = cells(lp_kernel.sig_lp_heap(bags, 8, f))
    same(want, cells(lp_kernel.sig_lp_arrow(bags, 8, f)))
    for flags in ({"order": "weight_asc"}, {"order": "weight_desc"}, {"variant": "one_pass", "early": False}, {"evict": False}):
        assert want == cells(lp_kernel.sig_lp_heap(bags, 8, f, **flags))


def test_spread_out_bags_and_merging(spark, bags):
    ladder = IntegerLadder(64)
    want = cells(poisson.sig_lp(bags, 8, ladder, Prng()))
    same(want, cells(poisson.sig_lp(bags, 8, ladder, Prng(), shards=7)))
    same(want, cells(lp_kernel.sig_lp_arrow(bags.repartition(5), 8, ladder)))
    parts = [lp_kernel.sig_lp_arrow(bags.where(F.col("elem") % 3 == i), 8, ladder) for i in range(3)]
    same(want, cells(poisson.merge_signatures(parts[0].unionByName(parts[1]).unionByName(parts[2]))))
    half = B.bag_scale(bags, 0.5)
    both = poisson.merge_signatures(lp_kernel.sig_lp_arrow(half, 8, ladder).unionByName(lp_kernel.sig_lp_arrow(bags, 8, ladder)))
    same(want, cells(both))


def test_tournament_equals_the_maximum():
    rng = np.random.default_rng(0)
    for m in range(1, 34):
        tree, plain = lp_kernel.MaxTree(m), [np.inf] * m
        for _ in range(60):
            j, x = int(rng.integers(m)), float(rng.random())
            tree.update(j, x)
            plain[j] = min(plain[j], x)
            assert tree.root == max(plain)


def test_cost_follows_theory(spark):
    one = spark.range(60).select(F.col("id").alias("bag_id"), F.xxhash64("id").alias("elem"), F.lit(1.0).alias("weight"))
    got = lp_kernel.lp_costs(one, 32, BinaryLadder(), "one_pass").agg(F.avg("n_points")).first()[0]
    assert abs(got / expected_points(32, 1) - 1) < 0.2
    big = verify.random_bags(spark, 300, 6)
    first, second = (lp_kernel.lp_costs(big, 32, FloatLadder(32), v).agg(F.avg("n_points"), F.avg("peak_nodes")).first() for v in ("one_pass", "two_phase"))
    assert second[0] < first[0]


def test_component_minima_are_exponential(spark):
    big = verify.random_bags(spark, 50, 60)
    totals = B.totals(big)
    sig = lp_kernel.sig_lp_arrow(big, 64, FloatLadder(32)).join(totals, "bag_id")
    x = np.sort([r[0] for r in sig.select(F.col("h") * F.col("total") / 64).collect()])
    gap = np.abs(1 - np.exp(-x) - np.arange(1, len(x) + 1) / len(x)).max()
    assert gap < 1.95 / np.sqrt(len(x))


def test_errors_follow_theory_and_controls_fail(spark):
    rows = verify.mse_table(spark, ["V1", "V3", "V7"], [64], 400).collect()
    z = {(r.alg, r.case): r.z for r in rows}
    assert all(abs(v) < 4 for (a, _), v in z.items() if a in ("lp", "lp_binary", "icws"))
    assert all(abs(v) < 4 for (_, c), v in z.items() if c == "V7")
    mse = {(r.alg, r.case): r.mse for r in rows}
    assert mse["zero_bit", "V1"] == pytest.approx(0.81) and mse["ccws", "V1"] == pytest.approx(0.01)
    assert all(z[a, "V3"] > 4 for a in ("zero_bit", "ccws", "pcws", "i2cws"))


def test_set_sketches_estimate_similarity(spark):
    pairs = verify.case_pairs(spark, "V8", 30)
    for run in (lambda b: baselines.sig_minhash(b, 64, Prng()), lambda b: baselines.sig_oph(b, 64, Prng(), "rotation"), lambda b: baselines.sig_oph(b, 64, Prng(), "random"), lambda b: baselines.sig_roundsketch(b, 64), lambda b: baselines.sig_permuted(b, 64), lambda b: baselines.sig_replicated(b, 64, Prng()), lambda b: baselines.sig_bounded(b, 64, Prng())):
        est = verify.pair_estimates(run(pairs), 64).agg(F.avg("est")).first()[0]
        assert abs(est - 0.8) < 0.05
    est = verify.pair_estimates(baselines.sig_cws(verify.case_pairs(spark, "V4", 60), 16), 16).agg(F.avg("est")).first()[0]
    assert abs(est - 0.5) < 0.1


def test_arrow_sampling_agrees_with_columns(bags):
    a, b = cells(baselines.sig_icws_arrow(bags, 8)), cells(baselines.sig_icws(bags, 8, Prng()))
    assert all(abs(a[k][1] - b[k][1]) <= 1e-9 * abs(b[k][1]) for k in b)


def test_kernels_agree_with_their_twins():
    from wsig.functions.prng import bernoulli_bits, np_exponential
    from wsig.surface import np_signature

    rng = np.random.default_rng(1)
    elem, weight = rng.integers(0, 10**9, 70), rng.exponential(2, 70)
    a, b = baselines.np_icws(elem, weight, 24), baselines.np_icws_blocks(elem, weight, 24, cells=100)
    assert a[0].tolist() == b[0].tolist() and np.allclose(a[1], b[1], rtol=1e-12)
    f = FloatLadder(32)
    ids, h = np_signature(elem, weight, 24, f)
    sig = lp_kernel.two_phase(list(zip(elem.tolist(), weight.tolist())), 24, f)
    assert np.allclose(h, sig.minima, rtol=1e-12) and len(ids) == 24
    x = np.sort(np_exponential(7, np.arange(40_000)))
    assert np.abs(1 - np.exp(-x) - np.arange(1, len(x) + 1) / len(x)).max() < 1.95 / np.sqrt(len(x))
    draws = [bernoulli_bits(0.3, int(b)) for b in rng.integers(0, 2**63, 20_000, dtype=np.uint64) * np.uint64(2)]
    assert abs(np.mean([d for d, _ in draws]) - 0.3) < 0.015 and abs(np.mean([n for _, n in draws]) - 2) < 0.05


def test_a_signature_of_16384_components_takes_bounded_chunks(spark, monkeypatch):
    rows = B.aggregate_bags(spark.range(60).select((F.col("id") % 3).alias("bag_id"), F.xxhash64("id").alias("elem"), (1 + F.col("id") % 7).cast("double").alias("weight")))
    assert [b - a for a, b in lp_kernel._chunks(np.array([5.0, 5.0, 50.0, 1.0, 1.0]), 10.0)] == [2, 1, 2]
    got = lp_kernel.sig_lp_arrow(rows, 16384, IntegerLadder(8)).groupBy("bag_id").count().collect()
    assert sorted(tuple(r) for r in got) == [(0, 16384), (1, 16384), (2, 16384)]


def test_specs_tell_comparable_signatures(spark):
    from wsig.surface import BagSignature, SignatureSpec, compare

    rows = spark.createDataFrame([(1, 5, 2.0), (2, 5, 2.0), (3, 6, 1.0)], "bag_id long, elem long, weight double")
    one, other = SignatureSpec(8, "integer:4"), SignatureSpec(8, "integer:4", salt=1)
    pairs = spark.createDataFrame([(1, 2), (1, 3)], "a long, b long")
    assert sorted(r.j for r in compare(one.sign(rows), one.sign(rows), pairs).collect()) == [0.0, 1.0]
    with pytest.raises(Exception, match="different specs"):
        compare(one.sign(rows), other.sign(rows), pairs).collect()
    with pytest.raises(ValueError, match="unknown ladder"):
        SignatureSpec(8, "odd").levels()
    assert BagSignature(m=8, ladder="integer:4").transform(rows).first()["spec"] == one.fingerprint


def test_edges(spark):
    rows = [(1, 5, 0.2), (2, 5, 3.0), (2, 6, 1.0), (3, 5, 3.0), (3, 6, 1.0), (4, 9, 2.0)]
    df = io.bags_from_rows(spark, rows)
    sig = poisson.assemble(lp_kernel.sig_lp_arrow(df, 16, IntegerLadder(8)), 16)
    assert sorted(r.bag_id for r in sig.collect()) == [2, 3, 4]  # bag 1 rounds to nothing
    pairs = spark.createDataFrame([(2, 3), (2, 4)], "a long, b long")
    assert {(r.a, r.b): r.j for r in lsh.estimate_pairs(sig, pairs).collect()} == {(2, 3): 1.0, (2, 4): 0.0}
    assert lp_kernel.sig_lp_arrow(df.limit(0), 4, IntegerLadder(8)).count() == 0
    bad = io.bags_from_rows(spark, [(1, 1, -1.0), (1, 2, float("nan")), (1, 3, 2.0), (None, 3, 2.0), (1, 4, 0.0)])
    assert check_bag(bad, "drop").count() == 1
    with pytest.raises(Exception, match="invalid weight"):
        check_bag(bad).collect()


def test_files_round_trip(spark, tmp_path):
    df = io.bags_from_rows(spark, [(1, 5, 0.25), (2, 6, 3.0)])
    for fmt in io.FORMATS:
        io.save_bags(df, str(tmp_path / fmt), fmt)
        assert sorted(io.load_bags(spark, str(tmp_path / fmt), fmt).collect()) == sorted(df.collect())
    io.write_signatures(df, str(tmp_path / "s"), "a")
    io.write_signatures(df.limit(1), str(tmp_path / "s"), "b")
    assert io.read_signatures(spark, str(tmp_path / "s"), "a").count() == 2


def test_search_operators(spark):
    edges = spark.createDataFrame([(1, 2), (2, 3), (7, 8), (9, 9)], "a long, b long")
    nodes = spark.range(1, 11).withColumnRenamed("id", "node")
    got = {r.node: r.cluster for r in lsh.components(nodes, edges).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 4: 4, 5: 5, 6: 6, 7: 7, 8: 7, 9: 9, 10: 10}
    keys = spark.createDataFrame([(i, 0, 5) for i in range(100)], "bag_id long, band int, bucket long")
    assert lsh.candidate_pairs(keys, 10).count() == 99 and lsh.candidate_pairs(keys, 100).count() == 4950


def test_filters_reach_the_scan(spark):
    plan = B.customer_part(spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "l_extendedprice" not in plan and plan.count("FileScan parquet") == 2
