"""Streams of weighted elements: windows of bags, late data, signatures kept up to date, joins of streams."""

from __future__ import annotations

import uuid

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from wsig.functions.ladder import Ladder
from wsig.operators.lp_kernel import _least, wavefront
from wsig.operators.lsh import shared_dir


def timed(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Events with ``ts`` as a timestamp and a watermark; rows later than the delay are dropped by stateful operators."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def window_bags(events: DataFrame, width: str, slide: str | None = None) -> DataFrame:
    """(user_id, event_type, start, weight): summed value in tumbling or sliding windows."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy("user_id", "event_type", w.alias("w")).agg(F.sum("value").alias("weight"), F.count("*").alias("n")).select("user_id", "event_type", F.col("w.start").alias("start"), "weight", "n")


def session_bags(events: DataFrame, gap: str) -> DataFrame:
    """(user_id, start, n, weight): sessions that end when nothing comes for the gap."""
    w = F.session_window("ts", gap)
    return events.groupBy("user_id", w.alias("w")).agg(F.sum("value").alias("weight"), F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n", "weight")


def stream_dedup(events: DataFrame, keys: list[str]) -> DataFrame:
    """The first row of each key within the watermark's delay."""
    return events.dropDuplicatesWithinWatermark(keys)


def stream_interval_pairs(left: DataFrame, right: DataFrame, gap: str = "1 hour") -> DataFrame:
    """Left events and right ones of the same user within the gap after them; both streams carry watermarks."""
    l = left.select(F.col("event_id").alias("l_id"), F.col("user_id").alias("l_user"), F.col("ts").alias("l_ts"))  # noqa: E741
    r = right.select(F.col("event_id").alias("r_id"), F.col("user_id").alias("r_user"), F.col("ts").alias("r_ts"))
    return l.join(r, F.expr(f"l_user = r_user AND r_ts >= l_ts AND r_ts <= l_ts + INTERVAL {gap}"))


def windowed_points(rows: DataFrame, points) -> DataFrame:
    """Least point of each (key, j) as an ordinary streaming aggregate: exact for element-wise maxima, with no weights kept."""
    best = F.min(F.struct("x", "id"))
    return points(rows).groupBy("bag_id", "j").agg(best.alias("p")).select("bag_id", "j", F.col("p.id").alias("id"), F.col("p.x").alias("h"))


def stream_signatures(rows: DataFrame, m: int, ladder: Ladder, salt: int = 0) -> DataFrame:
    """(bag_id, j, id, h) after each batch for the bags that it changed, from a stream of (bag_id, elem, weight).

    The state holds each element's summed weight and the m minima. A grown weight only adds points, so the element is
    walked again at its new weight and its points merged; a weight that falls makes the bag's minima anew.
    """

    def points(elem: np.ndarray, weight: np.ndarray):
        """Minima of some elements: their own horizon is raised until all components have a point."""
        level = ladder.np_index(weight)
        elem, level = elem[level >= 1], level[level >= 1]
        x, ids = np.full(m, np.inf), np.zeros(m, np.int64)
        if not len(elem):
            return x, ids
        total, c = ladder.np_value(level).sum(), np.log(m) + 4.0
        while True:
            horizon = np.array([m * c / total])
            _, j, px, pid = _least(*wavefront(np.zeros(len(elem), np.int64), elem, level, horizon, m, ladder, salt), m)
            if len(j) == m:
                x[j], ids[j] = px, pid
                return x, ids
            c *= 2

    def update(key, batches, state: GroupState):
        weights, x, ids = ({}, np.full(m, np.inf), np.zeros(m, np.int64))
        if state.exists:
            elems, w, x, ids = state.get
            weights, x, ids = dict(zip(elems, w)), np.array(x), np.array(ids)
        changed, fell = set(), False
        for pdf in batches:
            for e, w in zip(pdf["elem"].tolist(), pdf["weight"].tolist()):
                weights[e] = weights.get(e, 0.0) + w
                changed.add(e)
                fell = fell or w < 0
        if fell:
            weights = {e: w for e, w in weights.items() if w > 0}
            x, changed = np.full(m, np.inf), set(weights)
        elem = np.array(sorted(changed), np.int64)
        nx, nid = points(elem, np.array([weights[e] for e in elem.tolist()], float))
        better = (nx < x) | ((nx == x) & (nid < ids))
        x, ids = np.where(better, nx, x), np.where(better, nid, ids)
        state.update((list(weights), list(weights.values()), x.tolist(), ids.tolist()))
        yield pd.DataFrame({"bag_id": key[0], "j": np.arange(m, dtype=np.int32), "id": ids, "h": x})

    out, kept = "bag_id long, j int, id long, h double", "elems array<long>, weights array<double>, x array<double>, ids array<long>"
    return rows.groupBy("bag_id").applyInPandasWithState(update, out, kept, "update", GroupStateTimeout.NoTimeout)


def min_hashes(elements, m: int, salt: int = 0):
    """A set's minwise signature as a column over its array of long elements; null for an empty set."""
    of = lambda j: F.array_min(F.transform(elements, lambda e: F.xxhash64(F.lit(salt).cast("long"), e, j)))
    return F.when(F.size(elements) > 0, F.transform(F.sequence(F.lit(0).cast("long"), F.lit(m - 1).cast("long")), of))


def stream_match(arriving: DataFrame, stored: DataFrame, bands: int, rows: int) -> DataFrame:
    """(bag_id, stored_id) of arriving signatures (bag_id, sig) and stored ones that share a band; the store is a static table."""
    from wsig.operators.lsh import band_keys

    index = band_keys(stored, bands, rows).withColumnRenamed("bag_id", "stored_id")
    return band_keys(arriving, bands, rows).join(index, ["band", "bucket"]).select("bag_id", "stored_id")


def run_available_now(stream: DataFrame, mode: str = "complete", path: str | None = None) -> DataFrame:
    """Runs a stream over what is there and returns the result: the last batch's table, or all rows with their batch number.

    State and progress are in the shared folder, so a run that is started again on the same ``path`` goes on from there.
    """
    spark = stream.sparkSession
    path = path or f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"

    def sink(df: DataFrame, number: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/out/batch={number}")

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/checkpoint").foreachBatch(sink).trigger(availableNow=True).start()
    query.awaitTermination()
    rows = spark.read.option("basePath", f"{path}/out").parquet(f"{path}/out")
    if mode == "complete":
        return rows.where(F.col("batch") == rows.agg(F.max("batch")).first()[0]).drop("batch")
    return rows


def latest(rows: DataFrame, key: list[str]) -> DataFrame:
    """Of updates with batch numbers, the last of each key."""
    others = [c for c in rows.columns if c not in (*key, "batch")]
    best = F.max_by(F.struct(*others), "batch")
    return rows.groupBy(*key).agg(best.alias("r")).select(*key, "r.*")
