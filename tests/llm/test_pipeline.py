import re

import pytest
from pyspark.sql import types as T

corpus_pipeline = pytest.importorskip("corpus_pipeline")
from tests.llm.test_simhash import brute_components  # noqa: E402

from wsig.llm import mixing, pii, quality_rules  # noqa: E402

SF = "/root/testdata/sf0.001"


def test_run_against_each_stage_by_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    now, frames = docs, []
    for _, stage in corpus_pipeline.STAGES:
        now = stage(spark, now, SF)
        frames.append([r.asDict() for r in now.collect()])
        now = spark.createDataFrame(frames[-1], now.schema)
    start = [r.asDict() for r in docs.collect()]
    kept = {r.doc_id for r in quality_rules.quality_rules(docs).collect() if r.kept}
    assert sorted(map(str, frames[0])) == sorted(str(r) for r in start if r["doc_id"] in kept)
    survivors = {c for _, _, c in brute_components([(r["doc_id"], r["text"]) for r in frames[0]], corpus_pipeline.NEAR_BITS, corpus_pipeline.NEAR_SHINGLE)}
    assert sorted(map(str, frames[1])) == sorted(str(r) for r in frames[0] if r["doc_id"] in survivors)
    masked = [r | {"text": pii.mask(r["text"], pii.find(r["text"])[1])} for r in frames[1]]
    masked = [r | {"n_chars": len(r["text"])} for r in masked]
    assert sorted(map(str, frames[2])) == sorted(map(str, masked))
    assert not any(re.search(r"[a-z0-9]@[a-z0-9]+\.", r["text"]) for r in frames[2])
    taken = {r.doc_id: r.copies for r in mixing.mix_sources(spark.createDataFrame(frames[2], docs.schema)).collect()}
    assert sorted(map(str, frames[3])) == sorted(str(r) for r in frames[2] for _ in range(taken[r["doc_id"]]))
    assert len(frames[4]) == len(frames[3]) and all(r["lossless"] for r in frames[4])
    out = corpus_pipeline.run(spark, SF).collect()
    assert sorted(str(r.asDict()) for r in out) == sorted(map(str, frames[4]))


def test_stages_take_nulls_and_clashing_columns(spark):
    schema = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType()), T.StructField("kept", T.StringType()), T.StructField("position", T.StringType())])
    text = lambda i: " ".join(f"the {w}{i} of water" for w in ("stone", "river", "cloud", "field", "house", "winter", "garden", "morning"))
    rows = [(i, text(i), "en", "ab"[i % 2], 9, "c", "c") for i in range(30)] + [(None, text(77), None, None, None, None, None), (3, None, "en", "a", None, None, None), (4, "", None, "b", 0, "c", "c"), (0, text(0), "en", "a", 9, "c", "c")]
    for first in (rows, []):
        df = spark.createDataFrame(first, schema)
        for _, stage in corpus_pipeline.STAGES[:-1]:
            assert stage(spark, df, SF).columns == df.columns
            stage(spark, df, SF).collect()
            df = spark.createDataFrame([tuple(r) for r in stage(spark, df, SF).collect()], schema)
        corpus_pipeline.STAGES[-1][1](spark, df, SF).collect()
