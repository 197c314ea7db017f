import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from wsig.llm import mixing

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("source", T.StringType()), T.StructField("size", T.StringType())])


def table():
    rows, n = [], 0
    for source, docs, words in (("b", 400, 30), ("a", 40, 25), ("\U00010000", 60, 20), ("￿", 200, 10), (None, 100, 15)):
        for i in range(docs):
            rows.append((n, " ".join(["w x"] * (words + i % 7)), source, "clash"))
            n += 1
    return [*rows, (n, None, "b", None), (n + 1, "", "a", None), (None, "a b c", "b", None), (3, rows[3][1], "b", None), (3, rows[3][1], "b", None)]


def test_targets_and_words_taken(spark):
    rows = table()
    out = mixing.mix_sources(spark.createDataFrame(rows, SCHEMA).repartition(5))
    got = out.collect()
    assert len(got) == len(rows)
    size = {}
    for _, text, source, _ in rows:
        size[source] = size.get(source, 0) + len((text or "").encode().split())
    order = ["a", "b", "￿", "\U00010000", None]
    weights = dict(zip(order, (5, 2, 1, 5, 2)))
    target = {s: 0.0 for s in order}
    free, left = list(order), float(sum(size.values()))
    while free:  # water level by brute force
        unit = left / sum(weights[s] for s in free)
        over = [s for s in free if weights[s] * unit > 3 * size[s]]
        for s in over or free:
            target[s] = 3 * size[s] if over else weights[s] * unit
        left -= sum(target[s] for s in over)
        free = [s for s in free if s not in over] if over else []
    for s in order:
        mine = [r for r in got if r.source == s]
        assert {r.source_size for r in mine} == {size[s]}
        assert [r.target for r in mine] == pytest.approx([target[s]] * len(mine))
        assert abs(sum(r.taken for r in mine) - target[s]) <= max(r.size for r in mine) / 2
        assert all(r.taken <= 3 * r.size and 0 <= r.position <= 1 for r in mine)
    again = mixing.mix_sources(spark.createDataFrame(rows[::-1], SCHEMA).repartition(2)).collect()
    assert sorted(map(str, got)) == sorted(map(str, again))


def test_schedule_is_inverted_and_sorted(spark):
    out = mixing.mix_sources(spark.createDataFrame(table(), SCHEMA))
    copies = mixing.copy_positions(out)
    assert copies.count() == out.agg(F.sum("copies")).first()[0]
    per = [[r.position for r in part] for part in copies.rdd.glom().collect()]
    flat = [p for part in per for p in part]
    assert flat == sorted(flat)
    for schedule in mixing.SCHEDULES:
        for u in (0.0, 0.1, 0.37, 0.5, 0.9, 1.0):
            t = spark.range(1).select(mixing.position(schedule, F.lit(u))).first()[0]
            knots, area = mixing.demand_knots(schedule), 0.0
            for (t0, w0, _), (t1, w1, _) in zip(knots, knots[1:]):
                end = min(t, t1)
                if end > t0:
                    w = w0 + (w1 - w0) * (end - t0) / (t1 - t0)
                    area += (end - t0) * (w0 + w) / 2
            assert area == pytest.approx(u, abs=1e-9)


def test_falling_schedule_comes_early(spark):
    rows = [(i, "a b c d", s, None) for i in range(300) for s in ("x", "y", "z")]
    out = mixing.copy_positions(mixing.mix_sources(spark.createDataFrame(rows, SCHEMA), weights=(1.0,)))
    mean = {r.source: r[1] for r in out.groupBy("source").agg(F.avg("position")).collect()}
    assert mean["x"] < mean["y"] < mean["z"]


def test_one_document_makes_good_what_is_missing(spark):
    rows = [(i, "w " * n, "a", None) for i, n in enumerate([1, 2, 3, 5, 8, 13, 21, 34, 55, 89, 144, 233])] + [(100 + i, "w " * 40, "b", None) for i in range(10)]
    got = mixing.mix_sources(spark.createDataFrame(rows, SCHEMA), weights=(5.0, 2.3)).collect()
    for s in "ab":
        mine = [r for r in got if r.source == s]
        off, laps = mine[0].target - sum(r.taken for r in mine), mine[0].target // mine[0].source_size
        assert abs(off) <= 20
        for r in mine:  # no other single change is better
            assert abs(off - (r.size if r.copies == laps else -r.size)) >= abs(off) - 1e-9


def test_training_order_with_repeated_rows_and_clashing_names(spark):
    schema = T.StructType([*SCHEMA.fields, T.StructField("k1", T.StringType()), T.StructField("Position", T.StringType()), T.StructField("lang", T.StringType())])
    rows = [(None, "", None, "z", "k", "p", "en")] * 40 + [(None, "", None, "z", None, "p", "de")] * 3 + [(i, "a b " * (1 + i % 5), "s", None, "k", "p", None) for i in range(60)] + [(5, "a b ", "s", None, "k", "p", None)] * 2
    df = spark.createDataFrame(rows, schema).repartition(3)
    out = mixing.in_training_order(df)
    assert out.columns == df.columns
    taken = {}
    for r in mixing.mix_sources(df).collect():
        taken[r.k1] = taken.get(r.k1, 0) + r.copies
    want = {}
    for r in df.select(*df.columns, mixing.row_keys(df.columns)[0].alias("key")).distinct().collect():
        want[tuple(r)[:-1]] = taken[r.key]
    got = {}
    for r in out.collect():
        got[tuple(r)] = got.get(tuple(r), 0) + 1
    assert got == {k: v for k, v in want.items() if v}


def test_empty_and_wordless(spark):
    assert mixing.mix_sources(spark.createDataFrame([], SCHEMA)).count() == 0
    got = mixing.mix_sources(spark.createDataFrame([(1, None, None, None), (2, " ", "a", None)], SCHEMA)).collect()
    assert [(r.size, r.target, r.taken) for r in got] == [(0, 0.0, 0), (0, 0.0, 0)]


def test_query_is_read_off_the_training_order(spark, tmp_path, monkeypatch):
    from wsig.llm import queries, shared

    tags, settle = [], shared.settle
    monkeypatch.setattr(shared, "settle", lambda df, tag: tags.append(tag) or settle(df, tag))
    docs = spark.createDataFrame([*table(), (9, None, "b", None), (9, None, "b", None)], SCHEMA)
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    got = queries.op5_mixing(spark, str(tmp_path)).collect()
    assert "training-order" in tags
    key = lambda r: str((r.doc_id, r.source, r.size, r.source_size, r.target, r.taken, r.copies, r.position))
    assert sorted(map(key, got)) == sorted(map(key, mixing.mix_sources(docs).collect()))
    assert all(r.position <= r.last_position <= 1 for r in got if r.taken) and any(r.position < r.last_position for r in got if r.taken)
