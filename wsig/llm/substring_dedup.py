"""Operator 4, substring duplicates by seed and extend on winnowed anchors.

Seeds: of the word k-grams in each window of ``WINDOW`` words the one with the smallest hash is its anchor, so windows
with the same words have the same anchor at the same place. Consecutive windows of one anchor make a run. Anchors are
joined across documents; those of one document only end here.

Extension: a run reaches as far to both sides of its anchor as its windows do. Runs whose whole extent is equal form a
class, and every run of a class but those of its first document is repeated whole; this settles copies of any number
without pairing them. Where an anchor has several classes, the first run of each is extended to both sides as far as it
agrees with a run of a smaller document: the runs of an anchor come together, one row each with the hashes of its
windows, and leave as maximal stretches (document, first window, number of windows). The windows of an anchor with over
``GROUP`` such runs are given longer anchors instead and judged in the same way, so no task holds a large group: what
only shared a short anchor parts there, in runs again and not window by window; the last anchors are as long as the
window, and all their runs are of one class. Stretches over the length threshold
(all are, at one window or more) join to maximal repeats, and their words are removed. All steps are aggregates, equi-joins
and sorts; none makes pairs.

Runs, classes and windows are compared by 128 bits of hash. Null, empty and short texts have no window and stay. Rows without a doc_id stay whole and
are nobody's source, as they have no place in the order; rows of one doc_id never remove from each other. Repeated rows
give repeated result rows. An empty table gives an empty result. Other columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wsig.llm import shared
from wsig.llm.textscan import Scan, mix, run_hash, run_sums, steps, windows

WINDOW, ANCHOR = 50, 8
#: Documents whose keys (16 bytes each) are broadcast to pick texts; more are joined by a shuffle.
MOST_KEYS = 500_000
#: Runs of one anchor that one task extends together.
GROUP = 1024
_ROWS = "doc_id long, th long, n_words long, sha string, runs array<struct<anchor:long,cls:long,at:int,n:short>>"


def _least_places(h: np.ndarray, width: int) -> np.ndarray:
    """For each i the place of the leftmost least value of h[i : i + width], by doubling."""
    place, length = np.arange(len(h)), 1
    join = lambda a, b: np.where(h[b] < h[a], b, a)
    while length * 2 <= width:
        place = join(place[:-length], place[length:])
        length *= 2
    rest = width - length
    return join(place[: len(place) - rest], place[rest:]) if rest else place


def runs_of(scan: Scan, window: int = WINDOW, anchor: int = ANCHOR, starts: np.ndarray | None = None) -> dict[str, np.ndarray]:
    """Runs of windows with one anchor: document, first window, number of windows, anchor hash, class hash; of all windows or those that start at the ascending ``starts``."""
    if starts is None:
        starts = scan.window_starts(window)
    if not len(starts):
        return {c: np.zeros(0, np.int64) for c in ("doc", "at", "n", "anchor", "cls")}
    words, second = scan.word_hash(), scan.word_hash(1)
    grams = windows(words, np.arange(len(words) - anchor + 1), anchor)
    place = _least_places(grams, window - anchor + 1)[starts]
    first = np.flatnonzero(np.concatenate(([True], (place[1:] != place[:-1]) | (starts[1:] != starts[:-1] + 1))))
    n = np.diff(np.append(first, len(starts)))
    at, where = starts[first], place[first]
    cls = run_hash(run_sums(second, 1), at, at + n + window - 1, 1)
    cls = mix(cls + ((where - at) * 1024 + n).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    doc = scan.doc[at]
    return {"doc": doc, "at": at - scan.first_word[doc], "n": n, "anchor": grams[where].view(np.int64), "cls": cls.view(np.int64)}


def _keyed(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long"), F.xxhash64("text").alias("th"), "text")


def _scan_rows(docs: DataFrame, window: int, anchor: int) -> DataFrame:
    def run(batches):
        for batch in steps(batches):
            scan = Scan(batch.column("text"))
            r = runs_of(scan, window, anchor)
            ends = np.searchsorted(r["doc"], np.arange(batch.num_rows + 1)).astype(np.int32)
            items = pa.StructArray.from_arrays([pa.array(r["anchor"].astype(np.int64)), pa.array(r["cls"].astype(np.int64)), pa.array(r["at"].astype(np.int32)), pa.array(r["n"].astype(np.int16))], ["anchor", "cls", "at", "n"])
            whole = scan.bytes.tobytes()
            sha = [hashlib.sha256(b" ".join(whole[a:b].split())).hexdigest() for a, b in zip(scan.offsets[:-1].tolist(), scan.offsets[1:].tolist())]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("th"), pa.array(scan.n_words.astype(np.int64)), pa.array(sha), pa.ListArray.from_arrays(pa.array(ends), items)], ["doc_id", "th", "n_words", "sha", "runs"])

    return _keyed(docs).mapInArrow(run, _ROWS)


def _texts(docs: DataFrame, keys: DataFrame) -> DataFrame:
    """Rows of the documents named by ``keys`` (doc_id, th): picked before any shuffle while the keys are few."""
    if keys.count() <= MOST_KEYS:
        keys = F.broadcast(keys)
    return _keyed(docs).join(keys, ["doc_id", "th"], "left_semi")


def _reaches(texts: DataFrame, runs: DataFrame, window: int) -> DataFrame:
    """(anchor, doc_id, th, at, w) for each of the given runs, w being the hashes of its windows; texts are distinct by key."""

    def run(batches):
        for batch in steps(batches):
            scan = Scan(batch.column("text"))
            lists = batch.column("runs")
            n_runs = np.diff(lists.offsets.to_numpy())
            items = lists.flatten()
            at, n = items.field("at").to_numpy(zero_copy_only=False).astype(np.int64), items.field("n").to_numpy(zero_copy_only=False).astype(np.int64)
            doc = np.repeat(np.arange(len(n_runs)), n_runs)
            ends = np.cumsum(n)
            starts = np.repeat(scan.first_word[doc] + at - (ends - n), n) + np.arange(int(n.sum()))
            w = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], ends)).astype(np.int32)), pa.array(windows(scan.word_hash(1), starts, window, 1).view(np.int64)))
            take = pa.array(doc)
            yield pa.RecordBatch.from_arrays([items.field("anchor"), batch.column("doc_id").take(take), batch.column("th").take(take), items.field("at"), w], ["anchor", "doc_id", "th", "at", "w"])

    listed = runs.groupBy("doc_id", "th").agg(F.collect_list(F.struct("anchor", "at", "n")).alias("runs"))
    return texts.join(listed, ["doc_id", "th"]).select("doc_id", "th", "text", "runs").mapInArrow(run, "anchor long, doc_id long, th long, at int, w array<long>")


def stretches(anchor: np.ndarray, doc: np.ndarray, n: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(run, first window, windows) of the stretches that runs share with a smaller document's run of the same anchor.

    Run i has ``n[i]`` window hashes, end to end in ``w``; whole anchors at a time.
    """
    run = np.repeat(np.arange(len(n)), n)
    place = np.arange(len(w)) - np.repeat(np.cumsum(n) - n, n)
    a, d = anchor[run], doc[run]
    order = np.lexsort((d, w, a))  # equal windows on end, the smallest document first
    new = np.concatenate(([True], (a[order][1:] != a[order][:-1]) | (w[order][1:] != w[order][:-1]))) if len(w) else np.zeros(0, bool)
    least = np.empty(len(w), doc.dtype)
    firsts = np.flatnonzero(new)
    least[order] = np.repeat(d[order][firsts], np.diff(np.append(firsts, len(w))))
    again = least < d
    begins = again & ~np.concatenate(([False], again[:-1] & (run[1:] == run[:-1])))[: len(w)]
    stops = again & ~np.concatenate((again[1:] & (run[1:] == run[:-1]), [False]))[: len(w)]
    b, e = np.flatnonzero(begins), np.flatnonzero(stops)
    return run[b], place[b], e - b + 1


_SPAN = "doc_id long, th long, at int, n short"


def _extended(reaches: DataFrame) -> DataFrame:
    """Stretches of the runs of anchors with at most GROUP runs each: whole anchors of a sorted partition at a time."""

    def judge(table: pa.Table) -> pa.RecordBatch:
        table = table.combine_chunks()
        get = lambda c: table.column(c).chunk(0).to_numpy(zero_copy_only=False)
        lists = table.column("w").chunk(0)
        run, first, n = stretches(get("anchor"), get("doc_id"), np.diff(lists.offsets.to_numpy()).astype(np.int64), lists.flatten().to_numpy(zero_copy_only=False))
        return pa.RecordBatch.from_arrays([pa.array(get("doc_id")[run]), pa.array(get("th")[run]), pa.array((get("at")[run] + first).astype(np.int32)), pa.array(n.astype(np.int16))], ["doc_id", "th", "at", "n"])

    def run(batches):
        held: list[pa.RecordBatch] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(batch)
            keys = batch.column("anchor").to_numpy(zero_copy_only=False)
            cut = int(np.searchsorted(keys, keys[-1]))
            if cut:  # the last anchor may go on in the next batch
                yield judge(pa.Table.from_batches([*held[:-1], batch.slice(0, cut)]))
                held = [batch.slice(cut)]
        if held:
            yield judge(pa.Table.from_batches(held))

    n = shared.slots(reaches.sparkSession)
    return reaches.repartition(n, "anchor").sortWithinPartitions("anchor").mapInArrow(run, _SPAN)


def _split(texts: DataFrame, runs: DataFrame, window: int, anchor: int) -> DataFrame:
    """(anchor, cls, doc_id, th, at, n): the windows of the given runs as runs of anchors of another length; texts are distinct by key."""

    def run(batches):
        for batch in steps(batches):
            scan = Scan(batch.column("text"))
            lists = batch.column("runs")
            doc = np.repeat(np.arange(batch.num_rows), np.diff(lists.offsets.to_numpy()))
            at, n = (lists.flatten().field(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("at", "n"))
            starts = np.repeat(scan.first_word[doc] + at - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
            r = runs_of(scan, window, anchor, np.sort(starts))
            take = pa.array(r["doc"])
            yield pa.RecordBatch.from_arrays([pa.array(r["anchor"]), pa.array(r["cls"]), batch.column("doc_id").take(take), batch.column("th").take(take), pa.array(r["at"].astype(np.int32)), pa.array(r["n"].astype(np.int16))], ["anchor", "cls", "doc_id", "th", "at", "n"])

    listed = runs.groupBy("doc_id", "th").agg(F.collect_list(F.struct("at", "n")).alias("runs"))
    return texts.join(listed, ["doc_id", "th"]).select("doc_id", "th", "text", "runs").mapInArrow(run, "anchor long, cls long, doc_id long, th long, at int, n short")


def _cut(texts: DataFrame, repeats: DataFrame, window: int) -> DataFrame:
    """Texts without the words of their repeats: doc_id, n_words, n_removed, sha and the kept text."""

    def run(batches):
        for batch in steps(batches):
            scan = Scan(batch.column("text"))
            lists = batch.column("spans")
            items, n_spans = lists.flatten(), np.diff(lists.offsets.to_numpy())
            at, n = items.field("at").to_numpy(zero_copy_only=False), items.field("n").to_numpy(zero_copy_only=False)
            first = scan.first_word[np.repeat(np.arange(len(n_spans)), n_spans)] + at
            edge = np.zeros(len(scan.doc) + 1, np.int64)
            np.add.at(edge, first, 1)
            np.add.at(edge, first + n + window - 1, -1)
            gone = np.cumsum(edge[:-1]) > 0
            whole, kept = scan.bytes.tobytes(), []
            for a, b, lo, hi in zip(scan.offsets[:-1].tolist(), scan.offsets[1:].tolist(), scan.first_word[:-1].tolist(), scan.first_word[1:].tolist()):
                words = whole[a:b].split()
                kept.append(b" ".join([w for w, g in zip(words, gone[lo:hi].tolist()) if not g]))
            sha = pa.array([hashlib.sha256(k).hexdigest() for k in kept])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(scan.n_words.astype(np.int64)), pa.array(scan.words_per_doc(gone)), sha, pa.array(kept, pa.binary()).cast(pa.string())], ["doc_id", "n_words", "n_removed", "sha", "kept_text"])

    listed = repeats.groupBy("doc_id", "th").agg(F.collect_list(F.struct("at", "n")).alias("spans"))
    return texts.join(listed, ["doc_id", "th"]).select("doc_id", "text", "spans").mapInArrow(run, "doc_id long, n_words long, n_removed long, sha string, kept_text string")


def _longer(anchor: int, window: int) -> int:
    """The length of anchor that takes the place of one that too many runs share: halfway to the window's, then the window's."""
    return (anchor + window) // 2 if 2 * anchor < window else window


def repeats(docs: DataFrame, rows: DataFrame, window: int = WINDOW, anchor: int = ANCHOR) -> DataFrame:
    """(doc_id, th, at, n): stretches of n repeated windows from word ``at``, over the rows that _scan_rows gives."""
    runs = rows.where("doc_id is not null").select("doc_id", "th", F.explode("runs").alias("r")).select("r.anchor", "r.cls", "doc_id", "th", "r.at", "r.n")
    ends = [f("doc_id").alias(a) for f, a in ((F.min, "lo"), (F.max, "hi"))] + [f("cls").alias(a) for f, a in ((F.min, "cls_lo"), (F.max, "cls_hi"))]
    # what is joined back on a skewed key is written first: a join of two exchanges is one whose large partitions Spark splits
    spark = docs.sparkSession
    found, scratch = [], []
    while True:
        seeds, seeds_path = shared.settle(runs.groupBy("anchor").agg(*ends).where("lo < hi").select("anchor", (F.col("cls_lo") != F.col("cls_hi")).alias("several")), "anchors")
        hits, hits_path = shared.settle(runs.join(seeds, "anchor"), "anchor-hits")
        classes, classes_path = shared.settle(hits.groupBy("anchor", "cls").agg(F.min("doc_id").alias("first")), "classes")
        judged, judged_path = shared.settle(hits.join(classes, ["anchor", "cls"]).select("anchor", "doc_id", "th", "at", "n", "first", "several"), "run-firsts")
        shared.drop(spark, seeds_path, hits_path, classes_path)
        found.append(judged.where("first < doc_id").select("doc_id", "th", "at", "n"))
        scratch.append(judged_path)
        if anchor == window:  # equal anchors are equal windows, so no run is left open
            break
        open_runs, open_path = shared.settle(judged.where("first = doc_id and several").select("anchor", "doc_id", "th", "at", "n").distinct(), "open-runs")
        large, large_path = shared.settle(open_runs.groupBy("anchor").count().where(F.col("count") > GROUP).select("anchor"), "large-anchors")
        scratch += [open_path, large_path]
        few = open_runs.join(large, "anchor", "left_anti")
        texts = _texts(docs, few.select("doc_id", "th").distinct()).dropDuplicates(["doc_id", "th"])
        found.append(_extended(_reaches(texts, few, window)))
        if large.isEmpty():
            break
        anchor = _longer(anchor, window)
        many = open_runs.join(large, "anchor", "left_semi")
        texts = _texts(docs, many.select("doc_id", "th").distinct()).dropDuplicates(["doc_id", "th"])
        runs, runs_path = shared.settle(_split(texts, many, window, anchor), "longer-runs")
        scratch.append(runs_path)
    whole = found[0]
    for more in found[1:]:
        whole = whole.unionByName(more)
    out, _ = shared.settle(whole.distinct(), "repeats")
    shared.drop(spark, *scratch)
    return out


def substring_dedup(docs: DataFrame, window: int = WINDOW, anchor: int = ANCHOR) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 and kept_text (null where nothing goes) for each row of ``docs``."""
    rows, _ = shared.settle(_scan_rows(docs, window, anchor), "runs")
    found = repeats(docs, rows, window, anchor)
    keys, _ = shared.settle(found.select("doc_id", "th").distinct(), "repeat-keys")
    cut = _cut(_texts(docs, keys), found, window).select("doc_id", "n_words", "n_removed", F.col("sha").alias("kept_sha256"), "kept_text")
    same = rows.select("doc_id", "th", "n_words", "sha").join(keys, ["doc_id", "th"], "left_anti")
    return same.select("doc_id", "n_words", F.lit(0).cast("long").alias("n_removed"), F.col("sha").alias("kept_sha256"), F.lit(None).cast("string").alias("kept_text")).unionByName(cut)
