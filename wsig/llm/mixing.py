"""Operator 5, mixing sources to target weights as a time-varying curriculum.

Every source has a weight schedule over training time in [0, 1], piecewise linear between knots. Its integral is the
source's cumulative token demand. A document's copies take up consecutive words of its source's demand, in keyed random
order; the demand curve, inverted, turns the middle of each copy's span into a training position, and documents are
range-sorted by position.

Targets: weights share all words of the table; a target stops at ``most`` times its source's size and what is over is
shared again by weight, until none is above. A source whose target is r times its size lies end to end floor(r)
times and once more in part: the extra copy goes to the documents whose middle falls below the target. What then is
missing or over is made good as nearly as one document can, by giving it the extra copy or taking it back. So each
source's words come within one document of its target, mostly far nearer, and no document is taken more than ceil(r) <= ``most`` times.

Prefix sums are exact and spread out: within (source, slice) and over slices of a source, where a slice is a range of
the random order and their number is the square root of the row count, so neither window holds over about that many rows.

A null or empty text has size 0 and its document is taken like others of its order, with 0 words; a null source is a
source of its own, ordered last; repeated rows are separate documents. If all sizes are 0 every target is 0. An empty
table gives an empty result.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wsig.llm import shared
from wsig.llm.textscan import Scan, steps

WEIGHTS = (5.0, 2.0, 1.0)
MOST = 3
#: Weight multipliers at times 0, 1/2 and 1, by a source's place in the order: falling, level, rising.
SCHEDULES = (((0.0, 1.5), (0.5, 1.0), (1.0, 0.5)), ((0.0, 1.0), (1.0, 1.0)), ((0.0, 0.5), (0.5, 1.0), (1.0, 1.5)))


def row_keys(columns: list[str]) -> tuple[Column, Column]:
    """128 bits of a whole row, nulls told from values."""
    parts = [x for c in columns for x in (F.col(f"`{c}`").isNull(), F.col(f"`{c}`"))]
    return F.xxhash64(*parts), F.xxhash64(F.lit(1), *parts)


def sizes(docs: DataFrame) -> DataFrame:
    """(doc_id, source, size, text_key, k1, k2): words of each whole text, a hash that tells rows of one id apart, and keys of the whole row."""

    def run(batches):
        for batch in steps(batches):
            scan = Scan(batch.column("text"))
            key = scan.hash_runs(scan.offsets[:-1], scan.offsets[1:])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("source"), pa.array(scan.n_words.astype(np.int64)), pa.array(key.view(np.int64)), batch.column("k1"), batch.column("k2")], ["doc_id", "source", "size", "text_key", "k1", "k2"])

    k1, k2 = row_keys(docs.columns)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), F.col("text").alias("text"), k1.alias("k1"), k2.alias("k2"))
    return rows.mapInArrow(run, "doc_id long, source string, size long, text_key long, k1 long, k2 long")


def share(weights: list[float], caps: list[float], total: float) -> list[float]:
    """``total`` by weight, none above its cap; what a cap turns away goes to the others by weight."""
    out = [0.0] * len(caps)
    free = list(range(len(caps)))
    left = float(total)
    while free and left > 0:
        unit = left / sum(weights[i] for i in free)
        full = [i for i in free if weights[i] * unit > caps[i]]
        if not full:
            for i in free:
                out[i] = weights[i] * unit
            break
        for i in full:
            out[i] = float(caps[i])
            left -= caps[i]
        gone = set(full)
        free = [i for i in free if i not in gone]
    return out


def demand_knots(schedule) -> list[tuple[float, float, float]]:
    """(time, weight, integral so far) at each knot, with the whole integral 1."""
    whole = sum((b - a) * (v + w) / 2 for (a, v), (b, w) in zip(schedule, schedule[1:]))
    out, done = [], 0.0
    for i, (t, w) in enumerate(schedule):
        if i:
            t0, w0 = schedule[i - 1]
            done += (t - t0) * (w0 + w) / 2 / whole
        out.append((t, w / whole, done))
    return out


def position(schedule, u: Column) -> Column:
    """The time by which a share ``u`` of the schedule's demand has arisen: its integral inverted, piece by piece."""
    knots = demand_knots(schedule)
    out = F.lit(1.0)
    for (t0, w0, d0), (t1, w1, d1) in reversed(list(zip(knots, knots[1:]))):
        slope = (w1 - w0) / (t1 - t0)
        over = u - F.lit(d0)
        # w0 x + slope x^2 / 2 = over, by the root that stays exact when the slope vanishes
        root = F.lit(2.0) * over / (F.lit(w0) + F.sqrt(F.greatest(F.lit(0.0), F.lit(w0 * w0) + F.lit(2 * slope) * over)))
        out = F.when(u <= F.lit(d1), F.lit(t0) + F.when(over > 0, root).otherwise(F.lit(0.0))).otherwise(out)
    return out


def targets(sized: DataFrame, weights=WEIGHTS, most: int = MOST) -> list[dict]:
    """Size, target and schedule number of every source, in order of code points, null last."""
    rows = sized.groupBy("source").agg(F.sum("size").alias("size"), F.count("*").alias("n")).collect()  # a row a source
    rows.sort(key=lambda r: (r["source"] is None, (r["source"] or "").encode("utf-32-be")))
    w = [weights[i % len(weights)] for i in range(len(rows))]
    total = sum(r["size"] for r in rows)
    shares = share(w, [most * r["size"] for r in rows], total)
    return [{"source": r["source"], "source_size": r["size"], "target": t, "place": i, "n": r["n"]} for i, (r, t) in enumerate(zip(rows, shares, strict=True))]


def mix_sources(docs: DataFrame, weights=WEIGHTS, most: int = MOST, schedules=SCHEDULES, seed: int = 11) -> DataFrame:
    """doc_id, source, text_key, size, source_size, target, copies, taken and position (of the first copy) for each row."""
    spark = docs.sparkSession
    sized, _ = shared.settle(sizes(docs), "sizes")
    plan = targets(sized, weights, most)
    n = sum(p["n"] for p in plan)
    schema = "source string, source_size long, target double, place int"
    table = spark.createDataFrame([(p["source"], p["source_size"], p["target"], p["place"]) for p in plan], schema)
    slices = max(1, math.isqrt(n))
    draw = F.xxhash64(F.lit(seed), "k1", "k2")
    rows = sized.withColumn("draw", draw).withColumn("slice", F.floor(F.shiftrightunsigned("draw", 1) / F.lit(2.0**63) * slices).cast("int"))
    sums = rows.groupBy("source", "slice").agg(F.sum("size").alias("slice_size"))
    before = Window.partitionBy("source").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("slice_start", F.coalesce(F.sum("slice_size").over(before), F.lit(0))).select(F.col("source").alias("s_source"), F.col("slice").alias("s_slice"), "slice_start")
    inside = Window.partitionBy("source", "slice").orderBy(F.shiftrightunsigned("draw", 1), "k1", "k2").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("in_slice", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    rows = rows.join(sums, F.col("source").eqNullSafe(F.col("s_source")) & (F.col("slice") == F.col("s_slice"))).withColumn("start", F.col("slice_start") + F.col("in_slice"))
    table = table.select(F.col("source").alias("t_source"), "source_size", "target", "place")
    if len(plan) <= 100_000:  # a row of four small values each: a few MB
        table = F.broadcast(table)
    rows = rows.join(table, F.col("source").eqNullSafe(F.col("t_source")))
    laps = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long")
    rest = F.col("target") - laps * F.col("source_size")
    middle = F.col("start") + F.col("size") / 2
    extra = (F.col("size") > 0) & (middle < rest) & (laps < most)
    rows = rows.withColumns({"laps": laps.cast("int"), "rest": rest, "middle": middle, "extra": extra.cast("int")})
    rows, _ = shared.settle(rows.select("doc_id", "source", "text_key", "k1", "k2", "size", "source_size", "target", "place", "draw", "start", "laps", "rest", "middle", "extra"), "mix-rows")
    flips = _flips(rows, most)
    if len(plan) <= 100_000:
        flips = F.broadcast(flips)
    rows = rows.join(flips, F.col("source").eqNullSafe(F.col("f_source")) & (F.col("start") == F.col("f_start")) & (F.col("size") > 0), "left")
    copies = F.col("laps") + F.when(F.col("f_start").isNull(), F.col("extra")).otherwise(1 - F.col("extra"))
    rows = rows.withColumn("copies", copies.cast("long"))
    first = _when(schedules, F.lit(0)).alias("position")
    return rows.select("doc_id", "source", "text_key", "k1", "k2", "size", "source_size", "target", "place", "middle", "copies", (F.col("copies") * F.col("size")).alias("taken"), first)


def _flips(rows: DataFrame, most: int) -> DataFrame:
    """(f_source, f_start): the document of each source whose extra copy, given or taken back, brings the words nearest to the target."""
    gaps = rows.groupBy("source").agg((F.max("rest") - F.sum(F.col("extra") * F.col("size"))).alias("gap")).select(F.col("source").alias("g_source"), "gap")
    tried = rows.where((F.col("size") > 0) & (F.col("laps") < most)).join(gaps, F.col("source").eqNullSafe(F.col("g_source")))
    left = F.abs(F.col("gap") - F.when(F.col("extra") == 0, F.col("size")).otherwise(-F.col("size")))
    best = F.min(F.struct(left.alias("left"), F.shiftrightunsigned("draw", 1).alias("draw"), "start")).alias("best")
    found = tried.groupBy("source").agg(best, F.max("gap").alias("gap")).where(F.col("best.left") < F.abs("gap"))
    return found.select(F.col("source").alias("f_source"), F.col("best.start").alias("f_start"))


def _when(schedules, copy: Column) -> Column:
    """Training time of a copy: where the middle of its span lies on its source's demand curve."""
    u = F.when(F.col("target") > 0, F.least(F.lit(1.0), (F.col("middle") + copy * F.col("source_size")) / F.col("target"))).otherwise(F.lit(0.0))
    kind = F.pmod("place", F.lit(len(schedules)))
    return F.coalesce(*[F.when(kind == i, position(s, u)) for i, s in enumerate(schedules)])


def curriculum(docs: DataFrame, weights=WEIGHTS, most: int = MOST, schedules=SCHEDULES, seed: int = 11) -> DataFrame:
    """doc_id, source, size, source_size, target, taken, copies, position and last_position of each row, read off the training order.

    Every copy is put at its time on its source's demand curve and the copies of all sources are range-sorted; what a
    row's copies in that order hold is what the mix takes of it. Rows without words, or of which no copy is taken, have no place in it.
    """
    mix, _ = shared.settle(mix_sources(docs, weights, most, schedules, seed), "mix")
    own = ["doc_id", "source", "k1", "k2", "size", "source_size", "target", "middle"]
    held = (F.col("size") > 0) & (F.col("copies") > 0)
    each = mix.where(held).withColumn("copy", F.explode(F.sequence(F.lit(0), (F.col("copies") - 1).cast("int"))))
    each = each.select(*own, "copy", _when(schedules, F.col("copy")).alias("at"))
    order, _ = shared.settle(each.repartitionByRange("at", "k1", "k2", "copy").sortWithinPartitions("at", "k1", "k2", "copy"), "training-order")
    # words come before a row's middle, so no two rows of one source with words share it
    taken = order.groupBy(*own).agg(F.sum("size").alias("taken"), F.count("*").alias("copies"), F.min("at").alias("position"), F.max("at").alias("last_position"))
    none = mix.where(~held).select(*own, F.lit(0).cast("long").alias("taken"), "copies", "position", F.lit(None).cast("double").alias("last_position"))
    return taken.unionByName(none).select("doc_id", "source", "size", "source_size", "target", "taken", "copies", "position", "last_position")


def copy_positions(mix: DataFrame, schedules=SCHEDULES) -> DataFrame:
    """A row for each copy taken, range-sorted by training position: doc_id, text_key, source, copy, position."""
    each = mix.where("copies > 0").withColumn("copy", F.explode(F.sequence(F.lit(0), (F.col("copies") - 1).cast("int"))))
    timed = each.select("doc_id", "text_key", "source", "copy", _when(schedules, F.col("copy")).alias("position"))
    return timed.repartitionByRange("position", "doc_id", "copy").sortWithinPartitions("position", "doc_id", "copy")


def in_training_order(docs: DataFrame, weights=WEIGHTS, most: int = MOST, schedules=SCHEDULES) -> DataFrame:
    """Rows of ``docs``, each as often as the mix takes it, range-sorted by training position.

    Rows that agree in every column are interchangeable: one of them meets the positions of all their copies, so a row
    that is repeated very often is never brought together, and Spark can split the join.
    """
    plan = mix_sources(docs, weights, most, schedules).where("copies > 0")
    k1, k2, p1, p2, position = shared.free(docs.columns, "k1", "k2", "p1", "p2", "position")
    positions = F.transform(F.sequence(F.lit(0), (F.col("copies") - 1).cast("int")), lambda c: _when(schedules, c))
    plan = plan.select(F.col("k1").alias(p1), F.col("k2").alias(p2), F.explode(positions).alias(position))
    one, two = row_keys(docs.columns)
    rows = docs.withColumns({k1: one, k2: two}).dropDuplicates([k1, k2])
    each = rows.join(plan, (F.col(k1) == F.col(p1)) & (F.col(k2) == F.col(p2)))
    return each.repartitionByRange(position, k1).sortWithinPartitions(position, k1).select(*[F.col(f"`{c}`") for c in docs.columns])
