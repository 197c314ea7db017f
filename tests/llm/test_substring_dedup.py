import hashlib

import numpy as np
from pyspark.sql import types as T

from wsig.llm import substring_dedup as S

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("th", T.StringType()), T.StructField("n_words", T.StringType())])


def brute(rows, window):
    words = [(i, (t or "").encode().split()) for i, t, *_ in rows]
    least = {}
    for i, w in words:
        if i is not None:
            for a in range(len(w) - window + 1):
                k = tuple(w[a : a + window])
                least[k] = min(least.get(k, i), i)
    out = []
    for i, w in words:
        gone = set()
        if i is not None:
            for a in range(len(w) - window + 1):
                if least[tuple(w[a : a + window])] < i:
                    gone.update(range(a, a + window))
        kept = b" ".join(x for a, x in enumerate(w) if a not in gone)
        out.append((-1 if i is None else i, len(w), len(gone), hashlib.sha256(kept).hexdigest()))
    return sorted(out)


def corpus(seed, vocabulary, n=60):
    rng = np.random.default_rng(seed)
    word = lambda k: [f"w{x}ü" for x in rng.integers(0, vocabulary, k)]
    passages = [word(int(k)) for k in (49, 50, 51, 60, 120, 300)]
    rows = []
    for i in range(n):
        t = word(int(rng.integers(0, 150)))
        for _ in range(int(rng.integers(0, 4))):
            p = passages[int(rng.integers(len(passages)))]
            a = int(rng.integers(0, max(1, len(p) // 3)))
            t += p[a : len(p) - int(rng.integers(0, 10))] + word(int(rng.integers(0, 40)))
        rows.append((int(rng.integers(0, n)), " ".join(t), "clash", "clash"))
    return rows + [(900 + i, "\t ".join(passages[4]), None, None) for i in range(9)] + [(901, " ".join(passages[4]), None, None), (None, " ".join(passages[5]), None, None), (1, None, None, None), (2, "", None, None), (3000, "a b " * 4000, None, None), (3001, "b " + "a b " * 90, None, None), rows[0]]


def check(spark, rows, window, anchor):
    got = S.substring_dedup(spark.createDataFrame(rows, SCHEMA).repartition(3), window, anchor).collect()
    assert sorted((-1 if r.doc_id is None else r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in got) == brute(rows, window)
    return got


def test_matches_brute_force(spark):
    check(spark, corpus(1, 5000), 50, 8)


def test_repetitive_words_and_the_shuffled_pick(spark, monkeypatch):
    monkeypatch.setattr(S, "MOST_KEYS", 0)
    got = check(spark, corpus(2, 2), 12, 3)
    assert any(r.n_removed and r.kept_text is not None for r in got)


def test_anchors_of_many_classes_are_dealt_by_windows(spark, monkeypatch):
    monkeypatch.setattr(S, "GROUP", 1)
    check(spark, corpus(3, 3), 12, 3)
    monkeypatch.setattr(S, "GROUP", 4)
    check(spark, corpus(4, 4000), 50, 8)


def test_windows_of_a_large_anchor_stay_in_runs(spark, monkeypatch):
    """What too many runs share goes on in runs of longer anchors, not in a row for each window."""
    rng = np.random.default_rng(6)
    word = lambda k: [f"w{x}" for x in rng.integers(0, 10**6, k)]
    passage = word(20)
    rows = [(i, " ".join(word(60) + passage + (passage if i % 9 == 0 else []) + word(60)), "", "") for i in range(40)]
    rows.append((99, " ".join(rows[3][1].split()[10:110]), "", ""))
    settle, made = S.shared.settle, {}

    def kept(df, tag):
        out = settle(df, tag)
        made.setdefault(tag, []).append(out[0].count() if tag != "open-runs" else out[0].selectExpr("sum(n)").first()[0])
        return out

    monkeypatch.setattr(S.shared, "settle", kept)
    monkeypatch.setattr(S, "GROUP", 4)
    check(spark, rows, 50, 8)
    assert 0 < 5 * made["longer-runs"][0] < made["open-runs"][0]


def test_stretches():
    anchor, doc, n = np.array([5, 5, 5, 6]), np.array([2, 1, 3, 9]), np.array([3, 2, 4, 2])
    w = np.array([10, 11, 12, 11, 12, 7, 10, 11, 8, 10, 11])
    run, first, count = S.stretches(anchor, doc, n, w)
    assert list(zip(run.tolist(), first.tolist(), count.tolist())) == [(0, 1, 2), (2, 1, 2)]
    assert all(len(x) == 0 for x in S.stretches(anchor[:0], doc[:0], n[:0], w[:0]))


def test_empty(spark):
    assert S.substring_dedup(spark.createDataFrame([], SCHEMA)).count() == 0
