"""Signatures of bags by Poisson points over (element, level), as DataFrame plans.

A bag's component j is the smallest of the points that its elements hold on the levels their weights reach. The levels
of an element form a fixed tree of halved ranges; every draw is keyed by the element and a tree node, never by the bag or
the order of work, so any way of visiting the points that matter gives the same signature (see ``lp_kernel`` for the
ways that keep a heap). Here a horizon takes the heap's place: a bag of total weight W has its largest minimum below
T = m (ln m + c) / W except with probability exp(-c), so the halving keeps what lies at or under T, in ceil(log2 L) narrow
rounds without a shuffle; bags with an empty component are done again with twice the horizon.

The match value of a component is the winner's identity: the element, the node where its point was made and the point's number there.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wsig.functions.ladder import Ladder, discretize
from wsig.functions.prng import COMPONENT, FIRST, NEXT, SIDE, Prng
from wsig.operators import bag_kernel
from wsig.operators.lsh import settle


def clustered(bags: DataFrame, shards: int = 1) -> DataFrame:
    """Bags' rows as they lie, or dealt to ``shards`` parts for each bag before they multiply."""
    if shards == 1:  # minima merge, so rows may stay where they are
        return bags
    return bags.withColumn("__shard", F.pmod(F.xxhash64("elem", F.lit(3)), F.lit(shards))).repartition("bag_id", "__shard").drop("__shard")


def least_points(points: DataFrame) -> DataFrame:
    """(bag_id, j, id, h): the smallest x of each component; partial sums before any shuffle. Ties go to the smaller id."""
    best = F.min(F.struct("x", "id"))
    return points.groupBy("bag_id", "j").agg(best.alias("p")).select("bag_id", "j", F.col("p.id").alias("id"), F.col("p.x").alias("h"))


def assemble(long: DataFrame, m: int) -> DataFrame:
    """(bag_id, sig, h): arrays of length m in order of j; a component without a point is null with h infinite."""
    got = long.groupBy("bag_id").agg(F.map_from_entries(F.collect_list(F.struct("j", F.struct("id", "h").alias("p")))).alias("by_j"))
    at = F.transform(F.sequence(F.lit(0), F.lit(m - 1)), lambda j: F.element_at("by_j", j))
    return got.select("bag_id", F.transform(at, lambda p: p["id"]).alias("sig"), F.transform(at, lambda p: F.coalesce(p["h"], F.lit(float("inf")))).alias("h"))


def merge_signatures(long: DataFrame) -> DataFrame:
    """Min-merge of signatures that carry the same bag_id: that of the element-wise maximum of the bags."""
    best = F.min(F.struct("h", "id"))
    return long.groupBy("bag_id", "j").agg(best.alias("p")).select("bag_id", "j", F.col("p.id").alias("id"), F.col("p.h").alias("h"))


def sig_direct(bags: DataFrame, m: int, ladder: Ladder, prng: Prng, shards: int = 1) -> DataFrame:
    """The definition: a draw for each element, reached level and component. O(L m n). A bag, or one of its ``shards``, must fit a task."""

    def score(u, level):
        return -np.log(u) / ((ladder.np_value(level) - ladder.np_value(level - 1)) / m)

    rows = discretize(bags, ladder).select("bag_id", "elem", F.col("level").alias("number"))
    won = bag_kernel.sig_units(rows, m, prng, FIRST, score, lambda elem, level, j: (elem, level, j, FIRST), shards)
    sigs = won.select("bag_id", "j", prng.identity("elem", "unit", "j", FIRST).alias("id"), "h")
    return sigs if shards == 1 else merge_signatures(sigs)


def with_horizon(rows: DataFrame, m: int, c: float) -> DataFrame:
    """Adds the bag's horizon to discretized rows."""
    weights = rows.groupBy("bag_id").agg(F.sum("level_weight").alias("total"))
    return rows.join(weights, "bag_id").withColumn("horizon", F.lit(m * (math.log(m) + c)) / F.col("total"))


def _node(elem, lo, hi, level, horizon, x, j, made_lo, made_hi):
    return F.struct(elem.alias("elem"), lo.alias("lo"), hi.alias("hi"), level.alias("level"), horizon.alias("horizon"), x.alias("x"), j.alias("j"), made_lo.alias("made_lo"), made_hi.alias("made_hi"))


def roots(rows: DataFrame, m: int, ladder: Ladder, prng: Prng) -> DataFrame:
    """Every element's whole level range with its first point."""
    lo, hi = F.lit(0).cast("long"), F.lit(ladder.top).cast("long")
    x = prng.exponential(ladder.value(hi) - ladder.value(lo), "elem", lo, hi, FIRST)
    node = _node(F.col("elem"), lo, hi, F.col("level"), F.col("horizon"), x, prng.uniform_int(m, "elem", lo, hi, COMPONENT), lo, hi)
    return rows.select("bag_id", node.alias("n")).select("bag_id", "n.*").where("x <= horizon")


def split_round(nodes: DataFrame, m: int, ladder: Ladder, prng: Prng) -> DataFrame:
    """Halves every range of several levels: one half keeps the point, the other draws a later one; what can't matter goes."""
    lo, hi, mid = F.col("lo"), F.col("hi"), F.floor((F.col("lo") + F.col("hi")) / 2).cast("long")
    v = ladder.value
    left = prng.bernoulli((v(mid) - v(lo)) / (v(hi) - v(lo)), "elem", lo, hi, SIDE)
    owner_lo, owner_hi = F.when(left, lo).otherwise(mid), F.when(left, mid).otherwise(hi)
    other_lo, other_hi = F.when(left, mid).otherwise(lo), F.when(left, hi).otherwise(mid)
    nodes = nodes.withColumns({"owner_lo": owner_lo, "owner_hi": owner_hi, "other_lo": other_lo, "other_hi": other_hi})
    own = [F.col(c) for c in ("level", "horizon")]
    o_lo, o_hi = F.col("other_lo"), F.col("other_hi")
    later = F.col("x") + prng.exponential(v(o_hi) - v(o_lo), "elem", o_lo, o_hi, FIRST)
    owner = _node(F.col("elem"), F.col("owner_lo"), F.col("owner_hi"), *own, F.col("x"), F.col("j"), F.col("made_lo"), F.col("made_hi"))
    other = _node(F.col("elem"), o_lo, o_hi, *own, later, prng.uniform_int(m, "elem", o_lo, o_hi, COMPONENT), o_lo, o_hi)
    same = _node(F.col("elem"), lo, hi, *own, F.col("x"), F.col("j"), F.col("made_lo"), F.col("made_hi"))
    halves = F.filter(F.when(hi - lo > 1, F.array(owner, other)).otherwise(F.array(same)), lambda n: (n["lo"] < n["level"]) & (n["x"] <= n["horizon"]))
    return nodes.select("bag_id", F.explode(halves).alias("n")).select("bag_id", "n.*")


def leaf_points(leaves: DataFrame, m: int, ladder: Ladder, prng: Prng) -> DataFrame:
    """All points of single levels up to the horizon: (bag_id, j, x, id)."""
    rate = ladder.value(F.col("hi")) - ladder.value(F.col("lo"))
    mean = rate * F.col("horizon")
    most = F.ceil(mean + 10 * F.sqrt(mean) + 20).cast("int")
    gap = lambda k: prng.exponential(F.col("rate"), "elem", "lo", "hi", F.lit(NEXT), k)
    none = F.array().cast("array<struct<x:double,k:int>>")
    walk = F.aggregate(
        F.sequence(F.lit(1), F.col("most")),
        F.struct(F.col("x").alias("x"), none.alias("points")),
        lambda s, k: F.when(s["x"] > F.col("horizon"), s).otherwise(_step(s, s["x"] + gap(k), k)),
    )
    rows = leaves.withColumns({"rate": rate, "most": most}).withColumn("walk", walk)
    after = F.filter(F.col("walk.points"), lambda p: p["x"] <= F.col("horizon"))
    whole = F.when(F.col("walk.x") > F.col("horizon"), after).otherwise(F.raise_error(F.lit("more points before the horizon than planned for")))
    first = rows.select("bag_id", "j", "x", prng.identity("elem", "made_lo", "made_hi", F.lit(0)).alias("id"))
    later = rows.select("bag_id", "elem", "lo", "hi", F.explode(whole).alias("p"))
    j = prng.uniform_int(m, "elem", "lo", "hi", F.lit(COMPONENT), "p.k")
    return first.unionByName(later.select("bag_id", j.alias("j"), F.col("p.x").alias("x"), prng.identity("elem", "lo", "hi", "p.k").alias("id")))


def _step(state, x, k):
    return F.struct(x.alias("x"), F.concat(state["points"], F.array(F.struct(x.alias("x"), k.cast("int").alias("k")))).alias("points"))


def _halved(rows: DataFrame, m: int, ladder: Ladder, prng: Prng) -> DataFrame:
    nodes = roots(rows, m, ladder, prng)
    for _ in range(ladder.depth):
        nodes = split_round(nodes, m, ladder, prng)
    return nodes


def _level_by_level(rows: DataFrame, m: int, ladder: Ladder, prng: Prng) -> DataFrame:
    levels = rows.select("bag_id", "elem", "horizon", F.explode(F.sequence(F.lit(1).cast("long"), F.col("level"))).alias("hi")).withColumn("lo", F.col("hi") - 1)
    rate = ladder.value(F.col("hi")) - ladder.value(F.col("lo"))
    firsts = levels.withColumns({"x": prng.exponential(rate, "elem", "lo", "hi", FIRST), "j": prng.uniform_int(m, "elem", "lo", "hi", COMPONENT), "made_lo": F.col("lo"), "made_hi": F.col("hi")})
    return firsts.where("x <= horizon")


def until_filled(rows: DataFrame, m: int, c: float, points) -> DataFrame:
    """Least points up to the horizon; bags that lack a component again with twice the horizon, until none does."""
    done = settle(least_points(points(with_horizon(rows, m, c))))
    while True:
        filled = done.groupBy("bag_id").agg(F.count("*").alias("filled")).where(F.col("filled") >= m).select("bag_id")
        short = rows.select("bag_id").distinct().join(filled, "bag_id", "left_anti")
        if short.isEmpty():
            return done
        c = 2 * (c + math.log(m)) - math.log(m)
        again = settle(least_points(points(with_horizon(rows.join(short, "bag_id", "left_semi"), m, c))))
        done = done.join(short, "bag_id", "left_anti").unionByName(again)


def sig_lp(bags: DataFrame, m: int, ladder: Ladder, prng: Prng, c: float = 4.0, shards: int = 1) -> DataFrame:
    """(bag_id, j, id, h) by halving to the horizon, all in SQL expressions; suits ladders of moderate depth."""
    rows = discretize(clustered(bags, shards), ladder)
    return until_filled(rows, m, c, lambda r: leaf_points(_halved(r, m, ladder, prng), m, ladder, prng))


def sig_ordered(bags: DataFrame, m: int, ladder: Ladder, prng: Prng, c: float = 4.0, shards: int = 1) -> DataFrame:
    """Ascending points of each (element, level) up to the horizon, with no halving. O(L) for each element; for sets O(1)."""
    rows = discretize(clustered(bags, shards), ladder)
    return until_filled(rows, m, c, lambda r: leaf_points(_level_by_level(r, m, ladder, prng), m, ladder, prng))
