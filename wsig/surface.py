"""How users reach the signatures: a spec that tells comparable ones, SQL functions, aggregates, table functions, ML stages."""

from __future__ import annotations

import hashlib
import json
from dataclasses import asdict, dataclass

import numpy as np
import pandas as pd
from pyspark import keyword_only
from pyspark.ml import Transformer
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.ml.util import DefaultParamsReadable, DefaultParamsWritable
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wsig.functions.estimate import bbit, estimate_jaccard
from wsig.functions.ladder import BinaryLadder, FloatLadder, GeometricLadder, IntegerLadder, Ladder
from wsig.operators.lp_kernel import _least, sig_lp_arrow, wavefront
from wsig.operators.poisson import assemble


@dataclass(frozen=True)
class SignatureSpec:
    """All that two signatures must share to be compared."""

    m: int = 256
    ladder: str = "float32"
    salt: int = 0
    bits: int = 64

    def levels(self) -> Ladder:
        """``binary``, ``float32``, ``float64``, ``integer:TOP`` or ``geometric:LOW:EPS:HIGH``."""
        kind, *rest = self.ladder.split(":")
        if kind == "geometric":
            low, eps, high = map(float, rest)
            return GeometricLadder(low, eps, high)
        made = {"binary": BinaryLadder, "float32": lambda: FloatLadder(32), "float64": lambda: FloatLadder(64), "integer": lambda: IntegerLadder(int(rest[0]))}
        if kind not in made:
            raise ValueError(f"unknown ladder {self.ladder}")
        return made[kind]()

    @property
    def fingerprint(self) -> str:
        return hashlib.sha256(json.dumps(asdict(self), sort_keys=True).encode()).hexdigest()[:16]

    def sign(self, bags: DataFrame) -> DataFrame:
        """(bag_id, sig, spec) of bags."""
        sigs = assemble(sig_lp_arrow(bags, self.m, self.levels(), salt=self.salt), self.m)
        column = F.col("sig") if self.bits == 64 else bbit("sig", self.bits).alias("sig")
        return sigs.select("bag_id", column, F.lit(self.fingerprint).alias("spec"))


def compare(left: DataFrame, right: DataFrame, pairs: DataFrame) -> DataFrame:
    """(a, b, j) of pairs of signed bags; fails on a pair whose signatures are of different specs."""
    rows = pairs.join(left.select(F.col("bag_id").alias("a"), F.col("sig").alias("sa"), F.col("spec").alias("pa")), "a")
    rows = rows.join(right.select(F.col("bag_id").alias("b"), F.col("sig").alias("sb"), F.col("spec").alias("pb")), "b")
    same = F.when(F.col("pa") == F.col("pb"), estimate_jaccard("sa", "sb")).otherwise(F.raise_error(F.concat(F.lit("signatures of different specs: "), "pa", F.lit(" and "), "pb")).cast("double"))
    return rows.select("a", "b", same.alias("j"))


def np_signature(elem: np.ndarray, weight: np.ndarray, m: int, ladder: Ladder, salt: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Winner ids and minima of one bag; its horizon is raised until every component has a point. Empty: no ids."""
    level = ladder.np_index(weight)
    elem, level = elem[level >= 1], level[level >= 1]
    if not len(elem):
        return np.zeros(0, np.int64), np.zeros(0)
    total, c = float(ladder.np_value(level).sum()), np.log(m) + 4.0
    while True:
        _, j, x, ids = _least(*wavefront(np.zeros(len(elem), np.int64), elem, level, np.array([m * c / total]), m, ladder, salt), m)
        if len(j) == m:
            return ids, x
        c *= 2


def lp_signature(spec: SignatureSpec):
    """A grouped aggregate: ``agg(lp_signature(spec)("elem", "weight"))`` gives the signature array of a group's bag, which must fit a task."""
    ladder, m, salt = spec.levels(), spec.m, spec.salt

    def sign(elem: pd.Series, weight: pd.Series) -> list:
        some = (elem.notna() & weight.notna()).to_numpy()
        return np_signature(elem[some].to_numpy().astype(np.int64), weight[some].to_numpy().astype(float), m, ladder, salt)[0].tolist()

    sign.__annotations__ = {"elem": pd.Series, "weight": pd.Series, "return": list}
    return F.pandas_udf(sign, "array<long>", F.PandasUDFType.GROUPED_AGG)


def split_levels(spec: SignatureSpec):
    """A table function (elem, weight, horizon) -> (j, x, id): an element's points at or under a horizon."""
    ladder, m, salt = spec.levels(), spec.m, spec.salt

    @F.udtf(returnType="j int, x double, id long")
    class SplitLevels:
        def eval(self, elem: int, weight: float, horizon: float):
            if elem is None or weight is None or horizon is None:
                return
            level = ladder.np_index(np.array([weight]))
            if level[0] < 1:
                return
            _, j, x, ids = wavefront(np.zeros(1, np.int64), np.array([elem]), level, np.array([horizon]), m, ladder, salt)
            for k in range(len(j)):
                yield int(j[k]), float(x[k]), int(ids[k])

    return SplitLevels


def register(spark: SparkSession, spec: SignatureSpec | None = None) -> None:
    """SQL names: lp_signature(elem, weight), split_levels(elem, weight, horizon), signature_jaccard(a, b)."""
    spec = spec or SignatureSpec()
    spark.udf.register("lp_signature", lp_signature(spec))
    spark.udtf.register("split_levels", split_levels(spec))
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION signature_jaccard(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS DOUBLE "
        "RETURN aggregate(zip_with(a, b, (x, y) -> IF(x = y, 1, 0)), 0, (s, v) -> s + v) / size(a)"
    )


class BagSignature(Transformer, DefaultParamsReadable, DefaultParamsWritable):
    """An ML stage from bags (bag_id, elem, weight) to signatures, or to hashed one-hot features of b bits."""

    m = Param(Params._dummy(), "m", "components", TypeConverters.toInt)
    ladder = Param(Params._dummy(), "ladder", "levels", TypeConverters.toString)
    salt = Param(Params._dummy(), "salt", "salt of the draws", TypeConverters.toInt)
    bits = Param(Params._dummy(), "bits", "bits of a feature; 0 for signatures", TypeConverters.toInt)

    @keyword_only
    def __init__(self, m: int = 256, ladder: str = "float32", salt: int = 0, bits: int = 0):
        super().__init__()
        self._setDefault(m=256, ladder="float32", salt=0, bits=0)
        self._set(**self._input_kwargs)

    def _transform(self, dataset: DataFrame) -> DataFrame:
        get = self.getOrDefault
        signed = SignatureSpec(get("m"), get("ladder"), get("salt")).sign(dataset)
        if not get("bits"):
            return signed
        from wsig.operators.lsh import one_hot_features

        return one_hot_features(signed, get("bits"))
