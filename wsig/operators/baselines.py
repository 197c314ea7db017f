"""The signatures that the Poisson one is compared with: set hashing, replication, consistent sampling, rejection, sketches.

All but the sketches are one plan: a row for each (element, component), a keyed score, and the least score of each
(bag, component); the score's draws are keyed by element, component and purpose.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wsig.functions.prng import U1, U2, U3, U4, U5, U6, U7, Prng, np_hash, np_u01
from wsig.operators import bag_kernel
from wsig.operators.lsh import settle
from wsig.operators.poisson import clustered, least_points, merge_signatures


def components(bags: DataFrame, m: int, shards: int = 1) -> DataFrame:
    """A row for each element and component; rows of a bag are brought together before they multiply."""
    return clustered(bags, shards).where("weight > 0").withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(m - 1))))


def _best(rows: DataFrame, score: Column, ident: Column) -> DataFrame:
    return least_points(rows.select("bag_id", "j", score.alias("x"), ident.alias("id")))


# --- sets --------------------------------------------------------------------------------------------------------------


def sig_minhash(sets: DataFrame, m: int, prng: Prng, shards: int = 1) -> DataFrame:
    """Classic minwise hashing: the least keyed hash of each component. O(m n)."""
    rows = components(sets, m, shards)
    return _best(rows, prng.u01("elem", "j", U1), prng.identity("elem"))


def sig_replicated(bags: DataFrame, m: int, prng: Prng, scale: float = 1.0, residual: str = "drop", shards: int = 1) -> DataFrame:
    """Each element as floor(scale weight) copies, hashed as a set; residual='random' adds one more with the keyed chance of the rest.

    A bag, or one of its ``shards``, must fit a task; its copies need not.
    """
    s = F.col("weight") * scale
    extra = F.when(prng.u01("elem", U7) < s - F.floor(s), 1).otherwise(0) if residual == "random" else F.lit(0)
    copies = (F.floor(s) + extra).cast("long")
    rows = bags.select("bag_id", "elem", copies.alias("number")).where("number >= 1")
    won = bag_kernel.sig_units(rows, m, prng, U1, lambda u, copy: u, lambda elem, copy, j: (elem, copy), shards)
    sigs = won.select("bag_id", "j", prng.identity("elem", "unit").alias("id"), "h")
    return sigs if shards == 1 else merge_signatures(sigs)


def sig_oph(sets: DataFrame, m: int, prng: Prng, densify: str | None = None) -> DataFrame:
    """One permutation: each element falls into one bin; densify='rotation' fills an empty bin from the next one, 'random' from keyed ones."""
    u = prng.u01("elem", U1)
    rows = sets.select("bag_id", prng.uniform_int(m, "elem", U2).alias("j"), u.alias("x"), prng.identity("elem").alias("id"))
    bins = least_points(rows)
    if densify is None:
        return bins
    whole = bins.select("bag_id").distinct().withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(m - 1))))
    full = whole.join(bins, ["bag_id", "j"], "left")
    if densify == "rotation":
        turned = full.unionByName(full.withColumn("j", F.col("j") + m))
        ahead = Window.partitionBy("bag_id").orderBy("j").rowsBetween(0, Window.unboundedFollowing)  # 2 m rows a bag
        found = F.first(F.when(F.col("h").isNotNull(), F.struct("j", "id", "h")), ignorenulls=True).over(ahead)
        filled = turned.withColumn("f", found).where(F.col("j") < m)
        moved = (F.col("f.j") - F.col("j")).cast("int")
        shown = F.concat_ws("|", F.col("f.id").cast("string"), moved.cast("string")) if prng.kind == "md5" else F.xxhash64("f.id", moved.cast("long"))
        return filled.select("bag_id", "j", F.when(moved == 0, F.col("f.id")).otherwise(shown).alias("id"), (F.col("f.h") + moved).alias("h"))
    if densify != "random":
        raise ValueError(f"unknown densification {densify}")
    by_bin = bins.groupBy("bag_id").agg(F.map_from_entries(F.collect_list(F.struct("j", F.struct("id", "h").alias("p")))).alias("bins"))
    probes = F.transform(F.sequence(F.lit(1), F.lit(16 * m)), lambda k: F.element_at("bins", F.least(F.floor(prng.u01("j", k, U3) * m), F.lit(m - 1)).cast("int")))
    tried = full.join(by_bin, "bag_id").withColumn("f", F.when(F.col("h").isNull(), F.get(F.filter(probes, lambda p: p.isNotNull()), F.lit(0))))
    spare = F.get(F.map_values("bins"), F.lit(0))
    got = F.coalesce("f", spare)
    return tried.select("bag_id", "j", F.coalesce("id", got["id"]).alias("id"), F.coalesce("h", got["h"]).alias("h"))


#: Cells (elements by components) that a kernel works on at once.
CELLS = 1 << 14


def _whole_bags(bags: DataFrame, kernel) -> DataFrame:
    """A numpy kernel on batches of many whole bags: (bag number, elem, weight, bags) to ids and h by bag and component. A bag must fit a task."""

    def judge(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
        bag, elem, weight = (np.concatenate([p.column(c).to_numpy(zero_copy_only=False) for p in parts]) for c in ("bag_id", "elem", "weight"))
        names, number = np.unique(bag, return_inverse=True)
        ids, h = kernel(number, elem, weight, len(names))
        m = h.shape[1]
        return pa.RecordBatch.from_arrays([pa.array(np.repeat(names, m)), pa.array(np.tile(np.arange(m, dtype=np.int32), len(names))), pa.array(ids.reshape(-1)), pa.array(h.reshape(-1))], ["bag_id", "j", "id", "h"])

    def run(batches):
        held: list[pa.RecordBatch] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(batch)
            keys = batch.column("bag_id").to_numpy(zero_copy_only=False)
            cut = int(np.searchsorted(keys, keys[-1]))
            if cut or len(held) > 1 and held[-2].column("bag_id")[-1] != held[-1].column("bag_id")[0]:
                yield judge([*held[:-1], batch.slice(0, cut)])  # the last bag may go on in the next batch
                held = [batch.slice(cut)]
        if held:
            yield judge(held)

    n = int(bags.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = bags.select("bag_id", "elem", "weight").where("bag_id is not null").repartition(n, "bag_id").sortWithinPartitions("bag_id")
    return rows.mapInArrow(run, "bag_id long, j int, id long, h double")


def _least_in_bags(bag: np.ndarray, elem: np.ndarray, weight: np.ndarray, n_bags: int, m: int, points):
    """Ids and least values by bag and component; ``points`` gives the values of elements by components and a function that names some of them."""
    ids, h = np.zeros((n_bags, m), np.int64), np.full((n_bags, m), np.inf)
    step = max(1, CELLS // m)
    for i in range(0, len(bag), step):
        part = bag[i : i + step]
        x, name = points(elem[i : i + step], weight[i : i + step])
        starts = np.flatnonzero(np.concatenate(([True], part[1:] != part[:-1])))
        low = np.minimum.reduceat(x, starts, axis=0)
        seg = np.repeat(np.arange(len(starts)), np.diff(np.append(starts, len(part))))
        at = np.minimum.reduceat(np.where(x == low[seg], np.arange(len(part))[:, None], len(part)), starts, axis=0)
        own, j = np.nonzero(low < h[part[starts]])
        ids[part[starts][own], j] = name(at[own, j], j)
        h[part[starts][own], j] = low[own, j]
    return ids, h


def round_sketches(bag: np.ndarray, elem: np.ndarray, n_bags: int, m: int, salt: int = 0):
    """For each bag 2 m rounds: in an early round each element goes to a keyed bin, in a late one to the round's own; value round + u; until all bins are full."""
    ids, h = np.zeros(n_bags * m, np.int64), np.full(n_bags * m, np.inf)
    for i in range(2 * m):
        if not len(elem):
            break
        u = np_u01(salt, elem, i, U1)
        bins = np.minimum((np_u01(salt, elem, i, U2) * m).astype(np.int64), m - 1) if i < m else np.full(len(elem), i - m)
        cell = bag * m + bins
        order = np.lexsort((elem, u, cell))
        first = order[np.concatenate(([True], cell[order][1:] != cell[order][:-1]))]
        first = first[np.isinf(h[cell[first]])]
        ids[cell[first]], h[cell[first]] = elem[first], i + u[first]
        going = ~np.isfinite(h.reshape(n_bags, m)).all(axis=1)[bag]
        bag, elem = bag[going], elem[going]
    return ids.reshape(n_bags, m), h.reshape(n_bags, m)


def permuted_points(elem: np.ndarray, m: int, salt: int = 0):
    """Each element's components in a keyed order: the k-th gets k + u."""
    e, j = elem[:, None], np.arange(m)[None, :]
    rank = np_u01(salt, e, j, U1).argsort(axis=1).argsort(axis=1)
    return rank + np_u01(salt, e, j, U2), lambda i, _: elem[i]


def sig_roundsketch(sets: DataFrame, m: int, salt: int = 0) -> DataFrame:
    return _whole_bags(sets, lambda b, e, w, n: round_sketches(b, e, n, m, salt))


def sig_permuted(sets: DataFrame, m: int, salt: int = 0) -> DataFrame:
    return _whole_bags(sets, lambda b, e, w, n: _least_in_bags(b, e, w, n, m, lambda e, w: permuted_points(e, m, salt)))


# --- consistent weighted sampling --------------------------------------------------------------------------------------


def _gamma2(prng: Prng, a: int, b: int) -> Column:
    return -F.log(prng.u01("elem", "j", a) * prng.u01("elem", "j", b))


def sig_icws(bags: DataFrame, m: int, prng: Prng, keep: str = "both", shards: int = 1) -> DataFrame:
    """Improved consistent weighted sampling; keep='element' forgets the level (0-bit)."""
    rows = components(bags, m, shards).withColumns({"r": _gamma2(prng, U1, U2), "c": _gamma2(prng, U3, U4), "b": prng.u01("elem", "j", U5)})
    rows = rows.withColumn("t", F.floor(F.log("weight") / F.col("r") + F.col("b")))
    y = F.exp(F.col("r") * (F.col("t") - F.col("b")))
    return _best(rows, F.col("c") / (y * F.exp("r")), prng.identity("elem", "t") if keep == "both" else prng.identity("elem"))


def sig_ccws(bags: DataFrame, m: int, prng: Prng, shards: int = 1) -> DataFrame:
    """Sampling on weights themselves instead of their logarithms; a negative control."""
    rows = components(bags, m, shards).withColumns({"r": F.sqrt(prng.u01("elem", "j", U1)), "c": _gamma2(prng, U3, U4), "b": prng.u01("elem", "j", U5)})
    rows = rows.withColumn("t", F.floor(F.col("weight") / F.col("r") + F.col("b")))
    y = F.col("r") * (F.col("t") - F.col("b"))
    return _best(rows, F.col("c") / y - 2 * F.col("r") * F.col("c"), prng.identity("elem", "t"))


def sig_pcws(bags: DataFrame, m: int, prng: Prng, shards: int = 1) -> DataFrame:
    """One uniform fewer than the improved scheme; a negative control."""
    rows = components(bags, m, shards).withColumns({"u": prng.u01("elem", "j", U1), "r": _gamma2(prng, U1, U2), "b": prng.u01("elem", "j", U5)})
    rows = rows.withColumn("t", F.floor(F.log("weight") / F.col("r") + F.col("b")))
    y = F.exp(F.col("r") * (F.col("t") - F.col("b")))
    return _best(rows, -F.log(prng.u01("elem", "j", U3)) * F.col("u") / y, prng.identity("elem", "t"))


def sig_i2cws(bags: DataFrame, m: int, prng: Prng, shards: int = 1) -> DataFrame:
    """The winner by one set of draws, its level by another; a negative control."""
    rows = components(bags, m, shards).withColumns({"r1": _gamma2(prng, U1, U2), "r2": _gamma2(prng, U3, U4), "b1": prng.u01("elem", "j", U5), "b2": prng.u01("elem", "j", U6), "c": _gamma2(prng, U7, U7 + 1)})
    t2 = F.floor(F.log("weight") / F.col("r2") + F.col("b2"))
    z = F.exp(F.col("r2") * (t2 - F.col("b2") + 1))
    t1 = F.floor(F.log("weight") / F.col("r1") + F.col("b1"))
    return _best(rows, F.col("c") / z, prng.identity("elem", t1))


def np_icws(elem: np.ndarray, weight: np.ndarray, m: int, salt: int = 0):
    """The improved scheme in numpy, a pass over the elements for each component."""
    ids, h = np.zeros(m, np.int64), np.zeros(m)
    log_w = np.log(weight)
    for j in range(m):
        u = [np_u01(salt, elem, j, k) for k in (U1, U2, U3, U4, U5)]
        r, c = -np.log(u[0] * u[1]), -np.log(u[2] * u[3])
        t = np.floor(log_w / r + u[4])
        a = c / (np.exp(r * (t - u[4])) * np.exp(r))
        k = int(a.argmin())
        ids[j], h[j] = np_hash(salt, elem[k], int(t[k])).view(np.int64), a[k]
    return ids, h


def np_icws_blocks(elem: np.ndarray, weight: np.ndarray, m: int, salt: int = 0, cells: int = 1 << 18):
    """The same over blocks of elements by components, so that neither few elements nor few components cost calls."""
    ids, h = np.zeros(m, np.int64), np.full(m, np.inf)
    step = max(1, cells // m)
    j = np.arange(m)[None, :]
    for i in range(0, len(elem), step):
        e, log_w = elem[i : i + step, None], np.log(weight[i : i + step, None])
        u = [np_u01(salt, e, j, k) for k in (U1, U2, U3, U4, U5)]
        r, c = -np.log(u[0] * u[1]), -np.log(u[2] * u[3])
        t = np.floor(log_w / r + u[4])
        a = c / np.exp(r * (t - u[4] + 1))
        best = a.argmin(axis=0)
        x = a[best, j[0]]
        better = x < h
        h[better] = x[better]
        ids[better] = np_hash(salt, e[best[better], 0], t[best[better], j[0][better]].astype(np.int64)).view(np.int64)
    return ids, h


#: Dyadic intervals under a weight's own that cws_points looks at; what lies lower has a share of 2**-40 of the weight.
LOWER = 40


def cws_points(elem: np.ndarray, weight: np.ndarray, m: int, salt: int = 0):
    """Consistent sampling on dyadic weight intervals (2**(k-1), 2**k].

    Each interval of an element holds a keyed process of (place, value) points. The least point of whole intervals below the
    weight comes from one draw each; in the weight's own interval the points are walked by rising value, each lower in
    place than the last, until one lies at or under the weight. The bag's sample is its least value.
    """
    j = np.arange(m)[None, :]
    e, w = elem[:, None], weight[:, None]
    own = np.ceil(np.log2(w)).astype(np.int64)
    floor = np.exp2(own - 1.0)
    e, w, own, floor, j = np.broadcast_arrays(e, w, own, floor, j)
    place, x, n, got = 2 * floor, np.zeros(e.shape), np.zeros(e.shape, np.int64), np.zeros(e.shape, bool)
    while not got.all():  # ends surely: each step shrinks the stretch, and an empty one gives way to the intervals below
        x = np.where(got, x, x - np.log(np_u01(salt, e, j, own, U1, n)) / (place - floor))
        place = np.where(got, place, floor + (place - floor) * np_u01(salt, e, j, own, U2, n))
        got = got | (place <= w)
        n = np.where(got, n, n + 1)
        x = np.where(~got & (place - floor <= (w - floor) * 1e-12), np.inf, x)
        got = got | np.isinf(x)
    best, level, number, begun = x, own, n, np_hash(salt, e, j)
    for step in range(1, LOWER):
        k = own - step
        low = -np.log(np_u01(k, U1, 0, seed=begun)) / np.exp2(k - 1.0)
        level, number, best = np.where(low < best, k, level), np.where(low < best, 0, number), np.minimum(low, best)
    return best, lambda i, j: np_hash(salt, elem[i], level[i, j], number[i, j]).view(np.int64)


def sig_cws(bags: DataFrame, m: int, salt: int = 0) -> DataFrame:
    return _whole_bags(bags, lambda b, e, w, n: _least_in_bags(b, e, w, n, m, lambda e, w: cws_points(e, w, m, salt)))


# --- rejection ---------------------------------------------------------------------------------------------------------


def sig_rejection(bags: DataFrame, m: int, bounds: DataFrame, prng: Prng, rounds: int = 64) -> DataFrame:
    """Keyed candidates on the line of all elements' upper bounds, in a fixed order; a component takes the first that a bag fills.

    ``bounds`` (elem, bound) covers the universe. The candidates of ``rounds`` tries are made once for all bags and placed
    by a range join on the running sum of bounds; a bag that fills none of them in some component gets more tries.
    """
    line = settle(universe_line(bounds))
    total, n = line.agg(F.max("end"), F.count("*")).first()
    spark, bags = bags.sparkSession, bags.select("bag_id", "elem", "weight")
    done, first, left = None, 0, bags
    while True:
        tries = spark.range(m * rounds).select((F.col("id") % m).cast("int").alias("j"), (F.floor(F.col("id") / m) + first).cast("int").alias("k"))
        hits = settle(place_on_line(tries.withColumn("at", prng.u01("j", "k", U1) * total), line, total, n))
        filled = left.join(hits, "elem").where("depth <= weight").groupBy("bag_id", "j").agg(F.min("k").alias("k"))
        got = filled.select("bag_id", "j", F.col("k").cast("long").alias("id"), F.col("k").cast("double").alias("h"))
        done = settle(got if done is None else least_rows(done.unionByName(got)))
        whole = done.groupBy("bag_id").agg(F.count("*").alias("n")).where(F.col("n") >= m).select("bag_id")
        left = bags.join(whole, "bag_id", "left_anti")
        if left.isEmpty():
            return done
        first += rounds
        rounds *= 2


def least_rows(rows: DataFrame) -> DataFrame:
    best = F.min(F.struct("h", "id"))
    return rows.groupBy("bag_id", "j").agg(best.alias("p")).select("bag_id", "j", F.col("p.id").alias("id"), F.col("p.h").alias("h"))


def universe_line(bounds: DataFrame) -> DataFrame:
    """Elements end to end by their bounds: (elem, bound, start, end).

    Prefix sums are taken in and over about sqrt(n) buckets of elements, so neither window holds more than about that many rows.
    """
    n = max(1, math.isqrt(bounds.count()))
    dealt = bounds.select("elem", "bound", F.pmod(F.xxhash64("elem", F.lit(41)), F.lit(n)).alias("bucket"))
    sums = dealt.groupBy("bucket").agg(F.sum("bound").alias("bucket_sum"))
    before = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)  # sqrt(n) rows
    sums = sums.select("bucket", F.coalesce(F.sum("bucket_sum").over(before), F.lit(0.0)).alias("bucket_start"))
    inside = Window.partitionBy("bucket").orderBy("elem").rowsBetween(Window.unboundedPreceding, -1)
    rows = dealt.withColumn("in_bucket", F.coalesce(F.sum("bound").over(inside), F.lit(0.0))).join(sums, "bucket")
    start = F.col("bucket_start") + F.col("in_bucket")
    return rows.select("elem", "bound", start.alias("start"), (start + F.col("bound")).alias("end"))


def place_on_line(points: DataFrame, line: DataFrame, total: float, n: int) -> DataFrame:
    """(j, k, elem, depth): the element that each point falls on, by an equi-join on cells of the line's mean element width."""
    width = total / max(1, n)
    cell = lambda c: F.floor(F.col(c) / width).cast("long")
    cells = line.withColumn("cell", F.explode(F.sequence(cell("start"), cell("end"))))
    asks = points.withColumn("cell", cell("at"))
    found = cells.join(asks.hint("merge"), "cell").where("at >= start and at < end")  # points grow with the universe, so neither side goes to the driver
    return found.select("j", "k", "elem", (F.col("at") - F.col("start")).alias("depth"))


def sig_bounded(bags: DataFrame, m: int, prng: Prng) -> DataFrame:
    """Rejection over a fixed universe: every element of the bags, bounded by its largest weight; the value is the number of tries."""
    bounds = bags.groupBy("elem").agg(F.max("weight").alias("bound"))
    return sig_rejection(bags, m, bounds, prng)


# --- timing twin -------------------------------------------------------------------------------------------------------


def sig_icws_arrow(bags: DataFrame, m: int, salt: int = 0) -> DataFrame:
    """The improved scheme by numpy for batches of whole or partial bags; partial minima merge."""

    def run(batches):
        for batch in batches:
            ids, bag = np.unique(batch.column("bag_id").to_numpy(zero_copy_only=False), return_inverse=True)
            elem, log_w = batch.column("elem").to_numpy(zero_copy_only=False), np.log(batch.column("weight").to_numpy(zero_copy_only=False))
            order = np.argsort(bag, kind="stable")
            starts = np.searchsorted(bag[order], np.arange(len(ids)))
            for j in range(m):
                u = [np_u01(salt, elem, j, k) for k in (U1, U2, U3, U4, U5)]
                r, c = -np.log(u[0] * u[1]), -np.log(u[2] * u[3])
                t = np.floor(log_w / r + u[4])
                a = (c / np.exp(r * (t - u[4] + 1)))[order]
                least = np.minimum.reduceat(a, starts)
                win = np.flatnonzero(a == np.repeat(least, np.diff(np.append(starts, len(a)))))
                win = win[np.concatenate(([True], np.diff(bag[order][win]) > 0))]
                who = order[win]
                ident = np_hash(salt, elem[who], t[who].astype(np.int64)).view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(np.full(len(ids), j, np.int32)), pa.array(least), pa.array(ident)], ["bag_id", "j", "x", "id"])

    part = bags.select("bag_id", "elem", "weight").repartition("bag_id").mapInArrow(run, "bag_id long, j int, x double, id long")
    return least_points(part)
