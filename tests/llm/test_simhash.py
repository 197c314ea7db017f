import numpy as np
import xxhash
from pyspark.sql import types as T

from wsig.llm import simhash

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("source", T.StringType()), T.StructField("fp", T.StringType()), T.StructField("component_id", T.StringType())])


def brute_fingerprint(text, shingle=4):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    shingles = [b" ".join(words[i : i + shingle]) for i in range(max(1, len(words) - shingle + 1))]
    h = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(rows, tau=4, shingle=4):
    fps = [brute_fingerprint(r[1], shingle) for r in rows]
    parent = list(range(len(rows)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= tau:
                parent[find(i)] = find(j)
    ids = {}
    for i, r in enumerate(rows):
        if r[0] is not None:
            ids[find(i)] = min(ids.get(find(i), r[0]), r[0])
    return sorted((r[0] if r[0] is not None else -1, fps[i], ids.get(find(i)) if ids.get(find(i)) is not None else -1) for i, r in enumerate(rows))


def corpus():
    rng = np.random.default_rng(5)
    words = [f"w{i}é" for i in range(60)]
    rows = []
    for i in range(120):
        base = list(rng.choice(words, rng.integers(3, 80)))
        rows.append((i, " ".join(base)))
        for _ in range(int(rng.integers(0, 4))):
            edited = list(base)
            edited[int(rng.integers(len(edited)))] = "X"
            rows.append((1000 + len(rows), "\n".join(edited)))
    rows += [(5000, None), (5001, ""), (5002, " \t "), (None, ""), (None, "only here with no id at all"), (None, "only here with no id at all"), (7, rows[0][1]), (0, rows[0][1]), (9000, "one"), (9001, "ONE"), (9002, "x " * 30000)]
    return [(a, b, "s", "clash", "clash") for a, b in rows]


def test_matches_brute_force(spark, monkeypatch):
    rows = corpus()
    want = brute_components(rows)
    df = spark.createDataFrame(rows, SCHEMA).repartition(3)
    for bucket in (2048, 4):  # small buckets take the open-mask and block paths
        monkeypatch.setattr(simhash, "BUCKET", bucket)
        got = sorted((r.doc_id if r.doc_id is not None else -1, r.fp % (1 << 64), r.component_id if r.component_id is not None else -1) for r in simhash.simhash_groups(df).collect())
        assert got == want


def test_near_dedup_keeps_one_row_of_each_group(spark):
    rows = corpus()
    kept = simhash.near_dedup(spark.createDataFrame(rows, SCHEMA)).collect()
    ids = sorted(r.doc_id for r in kept if r.doc_id is not None)
    assert ids == sorted({c for _, _, c in brute_components(rows) if c >= 0})
    assert [r.text for r in kept if r.doc_id is None] == ["only here with no id at all"]
    assert kept[0].source == "s" and kept[0].fp == "clash"


def test_clashing_names_and_a_wider_threshold(spark):
    rows = corpus()
    df = spark.createDataFrame(rows, SCHEMA).withColumnRenamed("source", "own_id").withColumnRenamed("component_id", "NTH")
    kept = simhash.near_dedup(df, 6, 5)
    assert kept.columns == df.columns
    assert sorted(r.doc_id for r in kept.collect() if r.doc_id is not None) == sorted({c for _, _, c in brute_components(rows, 6, 5) if c >= 0})


def test_empty_table(spark):
    assert simhash.simhash_groups(spark.createDataFrame([], SCHEMA)).count() == 0
    assert simhash.near_dedup(spark.createDataFrame([], SCHEMA)).count() == 0


def test_allocation_is_the_cheapest():
    from itertools import product

    rng = np.random.default_rng(1)
    costs = [sorted(rng.random(3)) for _ in range(4)]
    best = min(sum(c[t] if t >= 0 else 0 for c, t in zip(costs, ts)) for ts in product(range(-1, 3), repeat=4) if sum(t + 1 for t in ts) == 5)
    total, thresholds = simhash.allocate(costs, 4)
    assert abs(total - best) < 1e-12 and sum(t + 1 for t in thresholds) == 5


def test_planning_sends_the_driver_a_row_a_part(spark, monkeypatch):
    """The corpus's histograms stay with the executors, and no table of a join passes through the driver."""
    rng = np.random.default_rng(3)
    fps = np.unique(rng.integers(-(2**62), 2**62, 3000))
    nodes = spark.createDataFrame([(int(x),) for x in fps], "fp long")
    parts = [list(range(i, i + 8)) for i in range(0, 64, 8)]
    want = []
    for part in parts:
        value = sum(((fps.view(np.uint64) >> np.uint64(b)) & np.uint64(1)).astype(int) << i for i, b in enumerate(part))
        want.append(simhash.candidate_counts(np.bincount(value, minlength=256), 1))
    assert simhash.expected_pairs(nodes, parts, 1) == want
    plan = simhash.simhash_groups(spark.createDataFrame(corpus()[:50], SCHEMA))._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastExchange" not in plan


def test_freed_memory_goes_back_after_a_task():
    """A worker that is kept doesn't hold on to the batches of its last task."""
    import pyarrow as pa

    from wsig.llm import textscan

    calls = []
    kept, textscan.give_back = textscan.give_back, lambda: calls.append(1)
    try:
        batch = pa.RecordBatch.from_pydict({"text": ["a b", None, "c"]})
        assert sum(b.num_rows for b in textscan.steps(iter([batch]), size=2)) == 3
    finally:
        textscan.give_back = kept
    assert calls == [1]
