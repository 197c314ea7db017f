import numpy as np

from wsig.operators import bags as B


def test_equals_all_pairs(spark):
    """Pairs by the rarest elements are those of the inverted index, with ties at the threshold and frequent elements."""
    rng = np.random.default_rng(4)
    rows = []
    for bag in range(0, 120, 3):
        base = {int(e): float(w) for e, w in zip(rng.integers(0, 60, 12), rng.integers(1, 6, 12), strict=True)} | {1000: 2.0}
        near = dict(base)
        near[int(rng.integers(0, 60))] = float(rng.integers(1, 4))
        for i, x in enumerate((base, near, dict(list(base.items())[1:]))):
            rows += [(bag + i, e, w) for e, w in x.items()]
    rows += [(900, 1, 4.0), (901, 1, 5.0), (902, 7777, 1.0)]  # 0.8 to the digit, and nothing shared
    df = spark.createDataFrame(rows, "bag_id long, elem long, weight double")
    for tau in (0.5, 0.8, 0.9):
        want = sorted((r.a, r.b, round(r.j, 12)) for r in B.wjaccard_all_pairs(df).where(f"j >= {tau}").collect())
        assert want and sorted((r.a, r.b, round(r.j, 12)) for r in B.similar_pairs(df, tau).collect()) == want
