import numpy as np
from pyspark.sql import functions as F
from pyspark.sql import types as T

from wsig.llm import weak_label as W

SF = "/root/testdata/sf0.1"


def test_em_recovers_accuracies():
    rng = np.random.default_rng(0)
    y = rng.random(20000) < 0.8
    right, speaks = np.array([0.95, 0.9, 0.7, 0.6, 0.85]), np.array([0.9, 0.5, 0.8, 0.9, 0.4])
    agree = rng.random((20000, 5)) < right
    v = np.where(rng.random((20000, 5)) < speaks, np.where(agree == y[:, None], 2, 1), 0).astype(np.int8)
    pattern, count = np.unique(W.patterns(v), return_counts=True)
    m = W.LabelModel(pattern, count, 5)
    assert abs(m.prior - 0.8) < 0.03 and np.abs(m.accuracies() - right).max() < 0.05
    assert ((m.posterior(W.patterns(v)) > 0.5) == y).mean() > 0.93


def test_held_out_accuracy(spark):
    """Quality labels are used nowhere in training; toxicity is trained on half of the labels."""
    docs, labels = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "labels"))
    out = W.weak_label_quality(docs, labels.where("doc_id % 2 = 0")).join(labels, "doc_id").cache()
    good, bad = out.where("quality = 1"), out.where("quality = 0")
    assert good.where("kept").count() >= 0.97 * good.count() and bad.where("not kept").count() >= 0.75 * bad.count()
    unseen = out.where("doc_id % 2 = 1")
    assert unseen.where("toxic = 1 and flagged").count() >= 0.9 * unseen.where("toxic = 1").count()
    assert unseen.where("toxic = 0 and flagged").count() <= 0.02 * unseen.where("toxic = 0").count()


def test_what_is_drawn_depends_on_the_rows_alone(spark, monkeypatch):
    monkeypatch.setattr(W, "SAMPLE", 60)
    monkeypatch.setattr(W, "LABELLED", 40)
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet") for t in ("documents", "labels"))
    docs = docs.unionByName(docs.where("doc_id < 90"))
    strays = spark.range(10**6, 10**6 + 500).selectExpr("id AS doc_id", "0 AS quality", "1 AS toxic")
    runs = [sorted(map(tuple, W.weak_label_quality(docs.repartition(n), labels.unionByName(strays).repartition(n)).collect())) for n in (3, 7)]
    assert runs[0] == runs[1] and len(runs[0]) == docs.count() and all(r[5] is not None for r in runs[0])


def test_edges(spark):
    schema = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("score", T.StringType()), T.StructField("label", T.StringType())])
    text = " ".join(f"the w{i} of and" for i in range(50))
    rows = [(1, text, "c", "c"), (1, text, "c", "c"), (2, None, None, None), (3, "", None, None), (None, text, None, None), (4, "x| " * 90000, None, None)]
    labels = spark.createDataFrame([(1, None), (None, 1), (77, 1)], "doc_id long, toxic int")
    got = W.weak_label_quality(spark.createDataFrame(rows, schema), labels).collect()
    assert len(got) == 6 and all(r.label_score is None and not r.flagged for r in got)
    assert len({(r.score, r.kept) for r in got if r.doc_id in (1, None)}) == 1
    assert W.weak_label_quality(spark.createDataFrame([], schema), labels).count() == 0
    assert W.weak_label_quality(spark.createDataFrame(rows, schema)).agg(F.count("score")).first()[0] == 6
