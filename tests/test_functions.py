import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from wsig.functions import estimate as E
from wsig.functions.ladder import BinaryLadder, FloatLadder, GeometricLadder, IntegerLadder, ListLadder, eps_negligible
from wsig.functions.prng import Prng, np_hash, np_u01


def test_numpy_twin_of_the_hash(spark):
    keys = [(0, 1, 2), (5, -7, 1 << 40), (-1, 0, 3)]
    df = spark.createDataFrame(keys, "a long, b long, c long")
    got = [r[0] for r in df.select(F.xxhash64("a", "b", "c")).collect()]
    assert got == np_hash(*np.array(keys).T).view(np.int64).tolist()
    u = [r[0] for r in df.select(Prng(salt=4).u01("a", "b", "c")).collect()]
    assert u == np_u01(4, *np.array(keys).T).tolist()


@pytest.mark.parametrize("ladder", [BinaryLadder(), IntegerLadder(64), GeometricLadder(0.5, 0.07, 900.0), ListLadder([1, 3, 10, 100])])
def test_index_is_the_largest_level_reached(spark, ladder):
    w = np.concatenate([np.random.default_rng(0).exponential(40, 300), ladder.np_value(np.arange(1, min(ladder.top, 60) + 1)) * (1 + 1e-9), [0.01, 1e6]])
    i = ladder.np_index(w)
    v = ladder.np_value(i)
    assert (v <= w).all() and ((i == ladder.top) | (ladder.np_value(np.minimum(i + 1, ladder.top)) > w)).all()
    df = spark.createDataFrame([(float(x),) for x in w], "w double")
    rows = df.select("w", ladder.index(F.col("w")).alias("i")).withColumn("v", ladder.value(F.col("i"))).collect()
    assert [r.i for r in rows] == i.tolist() and np.allclose([r.v for r in rows], v, rtol=1e-12)


def test_float_levels():
    f = FloatLadder(32)
    assert f.top == 0x7F7FFFFF and f.np_index(np.array([1.0])).tolist() == [0x3F800000]
    w = np.random.default_rng(1).exponential(3, 500)
    v = f.np_value(f.np_index(w))
    assert (v <= w).all() and (w / v - 1 < 1.2e-7).all() and (f.np_value(f.np_index(w) + 1) > w).all()
    with pytest.raises(ValueError):
        f.np_index(np.array([1e39]))
    assert FloatLadder(64).np_value(FloatLadder(64).np_index(w)).tolist() == w.tolist()


@pytest.mark.parametrize("bits", [32, 64])
def test_float_levels_as_columns_agree_to_the_bit(spark, bits):
    f, rng = FloatLadder(bits), np.random.default_rng(bits)
    most = 127 if bits == 32 else 1022
    w = np.concatenate([np.ldexp(rng.random(400) + 0.5, rng.integers(-most - 20, most, 400)), 2.0 ** np.arange(-most, most, 13), np.nextafter(2.0 ** np.arange(-60, 60), 0), rng.exponential(3, 200), [0.0, -1.0, 1e-46 if bits == 32 else 5e-324, float(np.finfo(f.float).max)]])
    df = spark.createDataFrame([(float(x),) for x in w], "w double")
    rows = df.select("w", f.index(F.col("w")).alias("i")).withColumn("v", f.value(F.col("i"))).collect()
    assert [r.i for r in rows] == np.where(w > 0, f.np_index(np.maximum(w, 0)), 0).tolist()
    assert [r.v for r in rows] == f.np_value(np.array([r.i for r in rows])).tolist()
    with pytest.raises(Exception, match="too large"):
        spark.createDataFrame([(1e39 if bits == 32 else float("inf"),)], "w double").select(f.index(F.col("w"))).collect()


def test_estimates(spark):
    df = spark.createDataFrame([([1, 2, 3, 4], [1, 0, 3, 9]), ([None] * 4, [None] * 4), ([None] * 4, [1, 2, 3, 4])], "a array<long>, b array<long>")
    assert [r[0] for r in df.select(E.estimate_jaccard("a", "b")).collect()] == [0.5, None, 0.0]
    packed = df.limit(1).select(E.bbit_pack("a", 4).alias("p"), E.bbit("a", 4).alias("v")).first()
    assert [packed.p[0] >> 4, packed.p[0] & 15, packed.p[1] >> 4, packed.p[1] & 15] == packed.v


def test_closed_forms():
    assert E.estimator_variance(0.5, 4) == 0.0625 and E.estimator_variance(0.5, 4, 1) == 0.0625 + 0.125
    # fixed values: published errors and scores, whose formulas these are
    for j, m, mse, z in ((0.1, 4, 2.19e-2, -1.49), (0.2, 64, 2.63e-2, 672.0), (0.5, 1024, 5.25e-3, 1450.0), (0.6, 4096, 5.76e-5, -1.24)):
        got = E.zscore(mse, j, m, 10_000)
        assert abs(got - z) <= max(0.3, 0.01 * abs(z))
    assert eps_negligible(0.5, 1024, 1.19e-7) and not eps_negligible(1 - 1e-6, 10**6, 1e-6)
    assert E.expected_points(16, 1) == pytest.approx(16 * sum(1 / i for i in range(1, 17)))
    b, r = E.plan_bands(64, 0.8)
    assert b * r == 64 and E.collision_probability(0.9, b, r) > 0.8
    assert E.signature_bytes(256, 8) == 256 and math.isclose(E.collision_probability(1.0, 4, 4), 1.0)
