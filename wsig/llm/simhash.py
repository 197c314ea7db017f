"""Operator 3, SimHash near-duplicates by the generalised pigeonhole principle.

Fingerprints that differ in at most ``tau`` of 64 bits are linked. Bits are grouped into parts, correlated bits
together; part i gets a threshold t_i (-1: not probed) such that the sum of t_i + 1 is tau + 1. Then two linked
fingerprints differ in at most t_i bits of some part i. A dynamic programme chooses the thresholds, for several numbers
of parts, by the candidate pairs that the corpus's own histograms of part values predict. A part with t_i = 0 is probed
by its value, one with t_i = 1 by its value without each bit in turn. Candidates of a bucket are verified against the
whole fingerprint, in numpy; a bucket yields a star for each of its connected groups, never its pairs.

Buckets of over ``BUCKET`` fingerprints are probed again by the same principle on the bits that the bucket's key leaves
open; what is still larger is compared block against block in separate tasks. No bucket is capped.

Equal fingerprints are one node. A null, empty or blank text has fingerprint zero and is linked like any other.
Rows with a null doc_id get the smallest non-null id of their component, or null if it has none. Repeated rows are
separate rows of one component. An empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from wsig.llm import shared
from wsig.llm.components import components
from wsig.llm.textscan import as_bytes, steps

SHINGLE, TAU, SEED = 4, 4, 42
#: Fingerprints of one bucket that one task compares with each other.
BUCKET = 2048
#: Numbers of parts that the planner tries.
PARTS = (4, 5, 6)
#: Cost of one probe key in candidate pairs.
PROBE_COST = 8.0


def fingerprint(text: bytes, shingle: int = SHINGLE) -> int:
    words = text.lower().split()
    if not words:
        return 0
    line = b" ".join(words)
    if len(words) <= shingle:
        h = np.array([xxhash.xxh64_intdigest(line, SEED)], np.uint64)
    else:
        lengths = np.fromiter(map(len, words), np.int64, len(words))
        starts = np.zeros(len(words), np.int64)
        np.cumsum(lengths[:-1] + 1, out=starts[1:])
        ends = (starts + lengths)[shingle - 1 :].tolist()
        digest = xxhash.xxh64_intdigest
        h = np.fromiter((digest(line[a:b], SEED) for a, b in zip(starts.tolist(), ends)), np.uint64, len(ends))
    ones = np.zeros(64, np.int64)
    for i in range(0, len(h), 1 << 15):
        ones += np.unpackbits(h[i : i + (1 << 15)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(h), bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """(doc_id, fp) for each row; fp holds the 64 bits as a signed long."""

    def run(batches):
        for batch in steps(batches):
            data, offsets = as_bytes(batch.column("text"))
            whole = data.tobytes()
            fps = np.array([fingerprint(whole[a:b], shingle) for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist())], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(fps.view(np.int64))], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, fp long")


def _bits(fps: np.ndarray) -> np.ndarray:
    return np.unpackbits(fps.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")


def bit_statistics(nodes: DataFrame) -> tuple[int, np.ndarray]:
    """How often each pair of bits is set together, over all nodes."""

    def run(batches):
        n, both = 0, np.zeros((64, 64), np.int64)
        for batch in batches:
            bits = _bits(batch.column("fp").to_numpy(zero_copy_only=False)).astype(np.float32)
            both += (bits.T @ bits).astype(np.int64)
            n += len(bits)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(-1, 4096)), pa.array(np.append(n, both.reshape(-1)))], ["cell", "n"])

    rows = nodes.select("fp").mapInArrow(run, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
    cells = np.zeros(4097, np.int64)
    cells[rows.column("cell").to_numpy() + 1] = rows.column("n").to_numpy()
    return int(cells[0]), cells[1:].reshape(64, 64)


def group_bits(n: int, both: np.ndarray, parts: int) -> list[list[int]]:
    """Bits in parts of nearly equal width, each grown by the bit most correlated with it."""
    p = np.diag(both) / max(n, 1)
    sd = np.sqrt(np.maximum(p * (1 - p), 1e-12))
    corr = np.abs(both / max(n, 1) - np.outer(p, p)) / np.outer(sd, sd)
    np.fill_diagonal(corr, 0)
    free, out = set(range(64)), []
    for width in (len(x) for x in np.array_split(np.arange(64), parts)):
        part = [max(sorted(free), key=lambda b: corr[b, list(free)].sum())]
        free.discard(part[0])
        while len(part) < width:
            part.append(max(sorted(free), key=lambda b: corr[b, part].sum()))
            free.discard(part[-1])
        out.append(sorted(part))
    return out


def mask_of(bits) -> int:
    return sum(1 << b for b in bits)


def signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def part_values(nodes: DataFrame, parts: list[list[int]]) -> DataFrame:
    """(part, value, n): counts of each part's values over all nodes; a part has at most 16 bits, so its values are bounded."""

    def run(batches):
        sums = [np.zeros(1 << len(x), np.int64) for x in parts]
        for batch in batches:
            bits = _bits(batch.column("fp").to_numpy(zero_copy_only=False)).astype(np.int64)
            for s, x in zip(sums, parts, strict=True):
                s += np.bincount(bits[:, x] @ (1 << np.arange(len(x))), minlength=len(s))
        for i, s in enumerate(sums):
            v = np.flatnonzero(s)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(v), i)), pa.array(v), pa.array(s[v])], ["part", "value", "n"])

    return nodes.select("fp").mapInArrow(run, "part long, value long, n long").groupBy("part", "value").agg(F.sum("n").alias("n"))


def expected_pairs(nodes: DataFrame, parts: list[list[int]], most: int) -> list[list[float]]:
    """``candidate_counts`` of each part. The executors make them, so the driver gets a row a part and no histogram."""
    widths = [len(x) for x in parts]

    def count(table: pa.Table) -> pa.Table:
        part = table.column("part")[0].as_py()
        hist = np.zeros(1 << widths[part], np.int64)
        hist[table.column("value").to_numpy()] = table.column("n").to_numpy()
        return pa.table({"part": pa.array([part], pa.int64()), "pairs": pa.array([candidate_counts(hist, most)], pa.list_(pa.float64()))})

    rows = part_values(nodes, parts).groupBy("part").applyInArrow(count, "part long, pairs array<double>").collect()  # a row a part
    found = {r["part"]: r["pairs"] for r in rows}
    return [found.get(i, [0.0] * (most + 1)) for i in range(len(parts))]


def candidate_counts(hist: np.ndarray, most: int) -> list[float]:
    """Expected pairs (ordered) whose values lie within 0, 1, ... ``most`` bits, by the histogram of a part."""
    width = len(hist).bit_length() - 1
    values, h, out = np.arange(len(hist)), hist.astype(float), []
    total = 0.0
    for t in range(most + 1):
        for flip in combinations(range(width), t):
            total += float(h @ h[values ^ mask_of(flip)])
        out.append(total)
    return out


def allocate(costs: list[list[float]], tau: int) -> tuple[float, list[int]]:
    """Thresholds, -1 upwards, with sum of t + 1 equal to tau + 1 and the least total cost; costs[i][t] is part i's at t."""
    best: dict[int, tuple[float, list[int]]] = {0: (0.0, [])}
    for cost in costs:
        new: dict[int, tuple[float, list[int]]] = {}
        for used, (total, chosen) in best.items():
            for t in range(-1, len(cost)):
                if used + t + 1 <= tau + 1:
                    option = (total + (cost[t] if t >= 0 else 0.0), [*chosen, t])
                    if used + t + 1 not in new or option < new[used + t + 1]:
                        new[used + t + 1] = option
        best = new
    return best.get(tau + 1, (float("inf"), []))


def plan(nodes: DataFrame, tau: int) -> list[int]:
    """Masks to probe: two fingerprints within tau bits agree under at least one of them."""
    n, both = bit_statistics(nodes)
    choices = []
    tried = [group_bits(n, both, m) for m in PARTS if m <= tau + 2]
    counts = iter(expected_pairs(nodes, [x for parts in tried for x in parts], 1))
    for parts in tried:
        costs = []
        for x in parts:
            pairs = next(counts)
            probes = (1, len(x))
            costs.append([pairs[t] + PROBE_COST * n * probes[t] for t in range(2)])
        total, thresholds = allocate(costs, tau)
        choices.append((total, parts, thresholds))
    _, parts, thresholds = min(choices, key=lambda c: c[0])
    masks = []
    for x, t in zip(parts, thresholds, strict=True):
        if t == 0:
            masks.append(mask_of(x))
        elif t == 1:
            masks += [mask_of(set(x) - {b}) for b in x]
    return masks


def _open_masks(mask: int, tau: int) -> list[int]:
    """The bits that a mask leaves open, in tau + 1 parts: what agrees under the mask agrees on one of these as well."""
    left = [b for b in range(64) if not mask >> b & 1]
    return [mask_of(left[i :: tau + 1]) for i in range(tau + 1)]


def _stars(fps: np.ndarray, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each linked fingerprint and the smallest of its group, from pairs of places."""
    label = np.arange(len(fps))
    rank = np.argsort(np.argsort(fps, kind="stable"), kind="stable")
    label = rank.copy()
    while True:
        least = np.minimum(label[a], label[b])
        new = label.copy()
        np.minimum.at(new, a, least)
        np.minimum.at(new, b, least)
        by_rank = np.empty_like(new)
        by_rank[rank] = new
        new = np.minimum(new, by_rank[new])
        if (new == label).all():
            break
        label = new
    ordered = np.sort(fps, kind="stable")
    moved = label != rank
    return fps[moved], ordered[label[moved]]


def _compare(batches, tau: int):
    """Stars of each bucket of batches that are sorted by key; a bucket's rows may span batches."""

    def links(keys, fps):
        u = fps.view(np.uint64)
        a, b = [], []
        step = 1
        while step < len(keys):
            same = np.flatnonzero(keys[step:] == keys[:-step])
            if not len(same):
                break
            near = same[np.bitwise_count(u[same] ^ u[same + step]) <= tau]
            a.append(near)
            b.append(near + step)
            step += 1
        if not a:
            return None
        a, b = np.concatenate(a), np.concatenate(b)
        x, y = _stars(fps, a, b) if len(a) else (fps[:0], fps[:0])
        return pa.RecordBatch.from_arrays([pa.array(x), pa.array(y)], ["a", "b"]) if len(x) else None

    held_k, held_f = np.zeros(0, np.int64), np.zeros(0, np.int64)
    for batch in batches:
        held_k = np.concatenate([held_k, batch.column("key").to_numpy(zero_copy_only=False)])
        held_f = np.concatenate([held_f, batch.column("fp").to_numpy(zero_copy_only=False)])
        cut = int(np.searchsorted(held_k, held_k[-1])) if len(held_k) else 0
        if cut >= 1 << 14:
            out = links(held_k[:cut], held_f[:cut])
            if out is not None:
                yield out
            held_k, held_f = held_k[cut:], held_f[cut:]
    out = links(held_k, held_f)
    if out is not None:
        yield out


def _in_buckets(keyed: DataFrame, tau: int) -> DataFrame:
    """Stars of buckets of at most BUCKET rows."""
    n = shared.slots(keyed.sparkSession)
    return keyed.select("key", "fp").repartition(n, "key").sortWithinPartitions("key", "fp").mapInArrow(lambda it: _compare(it, tau), "a long, b long")


def _tiles(keyed: DataFrame, tau: int) -> DataFrame:
    """Stars of buckets of any size: blocks of about BUCKET / 2 rows, each against each in a bucket of its own."""
    blocks = F.ceil(F.col("bucket_rows") * 2 / BUCKET).cast("int")
    own = F.pmod(F.xxhash64(F.col("fp"), F.lit(7)), blocks).cast("int")
    dealt = keyed.select("fp", "key", own.alias("own"), blocks.alias("blocks"))
    dealt = dealt.select("fp", "key", "own", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    return _in_buckets(dealt.select("fp", F.xxhash64("key", F.least("own", "other"), F.greatest("own", "other")).alias("key")), tau)


def _dealt(df: DataFrame) -> DataFrame:
    """A side of a join that is dealt to tasks however small it is: a broadcast would pass through the driver's memory."""
    return df.hint("merge")


def _sized(keyed: DataFrame) -> DataFrame:
    return keyed.join(_dealt(keyed.groupBy("key").agg(F.count("*").alias("bucket_rows"))), "key")


def links(nodes: DataFrame, tau: int = TAU) -> DataFrame:
    """Edges (a, b) whose connected components are those of all fingerprints within tau bits."""
    masks = plan(nodes, tau)
    key = lambda i, m: F.struct(F.lit(i).alias("spec"), F.xxhash64(F.lit(i), F.col("fp").bitwiseAND(F.lit(signed(m)))).alias("key"))
    keyed = nodes.select("fp", F.explode(F.array(*[key(i, m) for i, m in enumerate(masks)])).alias("s")).select("fp", "s.spec", "s.key")
    first, _ = shared.settle(_sized(keyed).where("bucket_rows > 1"), "buckets")
    small = _in_buckets(first.where(F.col("bucket_rows") <= BUCKET), tau)
    open_masks = F.array(*[F.array(*[F.lit(signed(x)) for x in _open_masks(m, tau)]) for m in masks])
    again = first.where(F.col("bucket_rows") > BUCKET).select("fp", "key", F.posexplode(open_masks[F.col("spec")]).alias("part", "mask"))
    again = again.select("fp", F.xxhash64("key", "part", F.col("fp").bitwiseAND(F.col("mask"))).alias("key"))
    second, _ = shared.settle(_sized(again).where("bucket_rows > 1"), "open-buckets")
    return small.unionByName(_in_buckets(second.where(F.col("bucket_rows") <= BUCKET), tau)).unionByName(_tiles(second.where(F.col("bucket_rows") > BUCKET), tau))


def simhash_groups(docs: DataFrame, tau: int = TAU, shingle: int = SHINGLE) -> DataFrame:
    """(doc_id, fp, component_id) for each row of ``docs``."""
    rows, _ = shared.settle(fingerprints(docs, shingle), "fingerprints")
    nodes, _ = shared.settle(rows.groupBy("fp").agg(F.min("doc_id").alias("first_id")), "nodes")
    roots = components(links(nodes, tau)).select(F.col("node").alias("fp"), "root")
    rooted = nodes.join(_dealt(roots), "fp", "left").select("fp", "first_id", F.coalesce("root", "fp").alias("root"))
    least = rooted.groupBy("root").agg(F.min("first_id").alias("component_id"))
    named = rooted.join(_dealt(least), "root").select("fp", "component_id")
    return rows.join(_dealt(named), "fp").select("doc_id", "fp", "component_id")


def near_dedup(docs: DataFrame, tau: int = TAU, shingle: int = SHINGLE) -> DataFrame:
    """One row of ``docs`` for each component: that of the smallest doc_id.

    Where rows share that id, one of them stays, the least by its text's hash. Rows without an id stay if no row of
    their component has one; then too one of them stays.
    """
    named = [c for c in docs.columns if c not in ("doc_id", "text")]
    own_id, nth = shared.free(docs.columns, "own_id", "nth")
    groups = simhash_groups(docs, tau, shingle)
    alone = groups.where(F.col("component_id").isNull()).select("fp").distinct()
    chosen = groups.where(F.col("doc_id") == F.col("component_id")).select(F.col("doc_id").alias(own_id)).distinct()
    with_id = docs.join(_dealt(chosen), F.col("doc_id").cast("long") == F.col(own_id), "left_semi")
    order = Window.partitionBy("doc_id").orderBy(*[F.xxhash64(f"`{c}`") for c in ("text", *named)])
    kept = with_id.withColumn(nth, F.row_number().over(order)).where(F.col(nth) == 1).drop(nth)
    return kept.unionByName(_without_id(docs, alone, shingle))


def _without_id(docs: DataFrame, alone: DataFrame, shingle: int) -> DataFrame:
    """Of rows without an id, one for each fingerprint group that has no id at all."""
    named, (fp, own_fp) = docs.columns, shared.free(docs.columns, "fp", "own_fp")
    none = docs.where(F.col("doc_id").isNull())

    def run(batches):
        for batch in steps(batches):
            data, offsets = as_bytes(batch.column("text"))
            whole = data.tobytes()
            fps = np.array([fingerprint(whole[a:b], shingle) for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist())], np.uint64)
            yield batch.append_column(fp, pa.array(fps.view(np.int64)))

    schema = T.StructType([*docs.schema.fields, T.StructField(fp, T.LongType())])
    marked = none.mapInArrow(run, schema).join(_dealt(alone.withColumnRenamed("fp", own_fp)), F.col(fp) == F.col(own_fp), "left_semi")
    return marked.groupBy(fp).agg(F.min_by(F.struct(*[f"`{c}`" for c in named]), F.struct(*[F.xxhash64(f"`{c}`") for c in named])).alias(own_fp)).select(f"{own_fp}.*")
