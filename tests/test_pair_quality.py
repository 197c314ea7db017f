"""Quality of candidates over all documents, against all pairs listed."""

import numpy as np

from wsig import queries_more
from wsig.functions import estimate as E
from wsig.functions.ladder import BinaryLadder
from wsig.operators import bags as B
from wsig.operators import lp_kernel, lsh, poisson


def test_candidate_quality_counts_pairs_of_copies(spark, tmp_path):
    """Texts whose shingles are equal, near copies of them and others: no pair at the threshold is left out of the counts."""
    rng = np.random.default_rng(7)
    texts = []
    for i in range(12):
        words = [f"w{x}" for x in rng.integers(0, 400, 60)]
        near = [*words[:-1], "other"]
        texts += [" ".join(words)] * (1 + i % 4) + ["  ".join(words).upper()] * (i % 3) + [" ".join(near)] * (1 + i % 2)
    texts += [None, "...", "one two", "One, two!"]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3).write.parquet(str(tmp_path / "documents.parquet"))
    got = queries_more.candidate_quality(spark, str(tmp_path)).first()
    bags = lsh.settle(B.bag_from_text(B.load(spark, str(tmp_path), "documents"), "doc_id", "text", "shingle", 5, "binary"))
    sigs = poisson.assemble(lp_kernel.sig_lp_arrow(bags, 64, BinaryLadder()), 64)
    pairs = lambda df: {(r.a, r.b) for r in df.collect()}
    truth = pairs(B.wjaccard_all_pairs(bags).where("j >= 0.8"))
    found = pairs(lsh.candidate_pairs(lsh.band_keys(sigs, *E.bands_for_recall(64, 0.8))))
    assert len(truth) > 80 and (got.found, got.true, got.hit) == (len(found), len(truth), len(found & truth))
    assert got.recall == got.hit / got.true and got.precision == got.hit / got.found


def test_quality_without_pairs(spark):
    none = spark.createDataFrame([], "a long, b long")
    for classes in (None, spark.createDataFrame([(1, 1), (2, 2)], "rep long, bag_id long")):
        got = lsh.pair_quality(none, none, classes).first()
        assert got.hit == 0 and got.recall is None and got.precision is None
