"""Whole bags signed in one task against the DataFrame plans and the array forms."""

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from wsig.functions import estimate as E
from wsig.functions.ladder import BinaryLadder, GeometricLadder, IntegerLadder, discretize
from wsig.functions.prng import FIRST, U1, Prng
from wsig.operators import bag_kernel, baselines, lp_kernel, poisson

SF = "/root/testdata/sf0.001"


def bags_of(spark, seed=3):
    rng = np.random.default_rng(seed)
    rows = [(b, int(e), float(w)) for b in (-65, -64, -63, 0, 1, 2, 63, 64, 65, 127, 128, 200) for e in rng.choice(np.concatenate([rng.integers(-(2**63), 2**63 - 1, 30), np.arange(-30, 30)]), 12, replace=False) for w in [rng.exponential(20)]]
    rows += [(3, 7, 1.0), (4, -(2**63), 40.0), (66, 5, 0.2), (67, 5, 9.0)]  # one element; the least long; under the first level
    return spark.createDataFrame(rows, "bag_id long, elem long, weight double").repartition(3)


def cells(df):
    return {(r.bag_id, r.j): (r.id, round(r.h, 10)) for r in df.collect()}


@pytest.mark.parametrize("kind", ["md5", "xxhash64"])
@pytest.mark.parametrize("ladder", [GeometricLadder(1.0, 0.1, 128.0), IntegerLadder(64), BinaryLadder()])
def test_whole_bags_have_the_same_points(spark, kind, ladder):
    bags = bags_of(spark)
    want = cells(poisson.sig_lp(bags, 16, ladder, Prng(kind)))
    assert cells(bag_kernel.sig_whole(bags, 16, ladder, Prng(kind))) == want
    # a horizon so near that nearly every bag is done again
    assert cells(bag_kernel.sig_whole(bags, 16, ladder, Prng(kind), c=-2.0)) == want


def test_few_and_many_keys_are_hashed_alike(monkeypatch):
    draws = bag_kernel.TextDraws(5, IntegerLadder(64))
    elem = np.random.default_rng(1).integers(-(2**63), 2**63 - 1, 900)
    state = draws.node(draws.begin(elem), np.arange(900), np.arange(900) % 60, np.arange(900) % 60 + 3)
    many = [draws.u01(state, 4, k) for k in (1, 99, 123456)]
    monkeypatch.setattr(bag_kernel, "FEW", 10**9)
    assert all((draws.u01(state, 4, k) == x).all() for k, x in zip((1, 99, 123456), many))


def test_equal_points_go_to_the_smaller_identity():
    for order in ([0, 1], [1, 0]):
        for apart in (False, True):
            least = bag_kernel.Minima(1, 1, bag_kernel.TextDraws(0, BinaryLadder()))
            offers = [np.array(order)] if not apart else [np.array([i]) for i in order]
            for at in offers:  # as texts 10 comes before 9
                one = np.ones(len(at), np.int64)
                least.offer(0 * at, 0.0 * at, 0.5 + 0.0 * at, np.array([9, 10])[at], 0 * one, one, 0)
            assert least.made[0][0] == 10


@pytest.mark.parametrize("name", ["sig_lp_geometric", "sig_ordered_binary", "estimate_bbit"])
def test_only_winners_leave_the_task(spark, name):
    """No points or signatures are shuffled or written: the plan ends with the pass over whole bags."""
    plan = entry.queries()[name](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan[: plan.index("MapInArrow")]


def test_neighbours_match_as_their_signatures_do(spark, monkeypatch):
    monkeypatch.setattr(bag_kernel, "ROWS", 30)
    bags, m, ladder = bags_of(spark), 32, IntegerLadder(64)
    sigs = {r.bag_id: r.sig for r in poisson.assemble(lp_kernel.sig_lp_arrow(bags, m, ladder), m).collect()}
    rows = spark.createDataFrame([(a, a + 1, s, sigs[a + 1]) for a, s in sigs.items() if a + 1 in sigs], "a long, b long, sa array<long>, sb array<long>")
    want = rows.select("a", "b", E.estimate_jaccard("sa", "sb").alias("same"), *[E.estimate_jaccard(E.bbit("sa", b), E.bbit("sb", b)).alias(f"same{b}") for b in (1, 8)])
    got = bag_kernel.neighbour_matches(bags, m, ladder, (1, 8)).select("a", "b", *[(F.col(c) / m).alias(c) for c in ("same", "same1", "same8")])
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    assert {(r.a, r.b) for r in got.collect()} >= {(-65, -64), (-64, -63), (63, 64), (127, 128)} and 66 not in sigs


@pytest.mark.parametrize("kind", ["md5", "xxhash64"])
def test_units_are_drawn_as_the_definition_says(spark, monkeypatch, kind):
    """The least of all draws of units, in stretches that cut elements and bags, against a row for each draw."""
    monkeypatch.setattr(bag_kernel, "UNITS", 37)
    bags, prng, m, ladder = bags_of(spark), Prng(kind), 12, GeometricLadder(1.0, 0.3, 50.0)
    each = lambda rows: rows.withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(m - 1))))
    levels = each(discretize(bags, ladder).select("bag_id", "elem", F.explode(F.sequence(F.lit(1).cast("long"), "level")).alias("l")))
    rate = (ladder.value(F.col("l")) - ladder.value(F.col("l") - 1)) / m
    want = cells(poisson.least_points(levels.select("bag_id", "j", prng.exponential(rate, "elem", "l", "j", FIRST).alias("x"), prng.identity("elem", "l", "j", FIRST).alias("id"))))
    assert cells(poisson.sig_direct(bags, m, ladder, prng)) == want == cells(poisson.sig_direct(bags, m, ladder, prng, shards=3))
    copies = each(bags.where("weight * 3 >= 1").select("bag_id", "elem", F.explode(F.sequence(F.lit(1).cast("long"), F.floor(F.col("weight") * 3))).alias("copy")))
    want = cells(poisson.least_points(copies.select("bag_id", "j", prng.u01("elem", "copy", "j", U1).alias("x"), prng.identity("elem", "copy").alias("id"))))
    assert cells(baselines.sig_replicated(bags, m, prng, 3.0)) == want == cells(baselines.sig_replicated(bags, m, prng, 3.0, shards=3))


def test_equal_units_go_to_the_smaller_identity(monkeypatch):
    for units in (1, 2, 100):
        monkeypatch.setattr(bag_kernel, "UNITS", units)
        draws = bag_kernel.UnitTexts(0, 2)
        x, elem, unit = bag_kernel.least_units(np.array([0, 0, 1]), np.array([9, 10, 7]), np.array([1, 2, 1]), 2, 2, draws, 1, lambda u, l: 0 * u, lambda e, l, j: (e, l))
        assert (x == 0).all() and (elem == [[10, 10], [7, 7]]).all() and (unit == 1).all()  # as texts 10|1 comes before 9|1


@pytest.mark.parametrize("name", ["sig_direct_integer", "sig_replicated_whole"])
def test_units_do_not_become_rows(spark, name):
    """Draws stay in the task that has the bag: only winners come out of it, and none is sorted or shuffled."""
    plan = entry.queries()[name](spark, SF)._jdf.queryExecution().executedPlan().toString()
    above = plan[: plan.index("MapInArrow")]
    assert "Exchange" not in above and "Sort" not in above
