"""Ladders of weight levels: 0 = v_0 < v_1 < ... < v_L. A weight is rounded down to the largest level it reaches."""

from __future__ import annotations

import math
from bisect import bisect_right

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _let(value: Column, body) -> Column:
    """body(value), with the value computed once: a lambda's variable isn't copied into every place that uses it."""
    return F.element_at(F.transform(F.array(value), body), 1)


class Ladder:
    """index() and value() as columns, np_index() and np_value() in numpy; top is L."""

    top: int

    @property
    def depth(self) -> int:
        """Halvings from the whole range to one level."""
        return max(0, (self.top - 1).bit_length())

    def index(self, w: Column) -> Column:
        raise NotImplementedError

    def value(self, i: Column) -> Column:
        raise NotImplementedError

    def np_index(self, w: np.ndarray) -> np.ndarray:
        raise NotImplementedError

    def np_value(self, i: np.ndarray) -> np.ndarray:
        raise NotImplementedError

    def sql_index(self, w: str) -> str:
        raise NotImplementedError

    def sql_value(self, i: str) -> str:
        raise NotImplementedError

    @staticmethod
    def for_range(low: float, high: float, eps: float) -> GeometricLadder:
        """A geometric ladder that holds low .. high with relative error eps."""
        return GeometricLadder(low, eps, high)


class BinaryLadder(Ladder):
    """Levels 0 and 1: sets."""

    top = 1

    def index(self, w):
        return F.when(w >= 1, 1).otherwise(0).cast("long")

    def value(self, i):
        return i.cast("double")

    def np_index(self, w):
        return (np.asarray(w) >= 1).astype(np.int64)

    def np_value(self, i):
        return np.asarray(i, float)

    def sql_index(self, w):
        return f"(CASE WHEN {w} >= 1 THEN 1 ELSE 0 END)"

    def sql_value(self, i):
        return f"CAST({i} AS DOUBLE)"


class IntegerLadder(Ladder):
    """Levels 0 .. L; weights above L are clamped to it."""

    def __init__(self, top: int):
        self.top = top

    def index(self, w):
        return F.least(F.floor(w), F.lit(self.top)).cast("long")

    def value(self, i):
        return i.cast("double")

    def np_index(self, w):
        return np.minimum(np.floor(w), self.top).astype(np.int64)

    def np_value(self, i):
        return np.asarray(i, float)

    def sql_index(self, w):
        return f"CAST(least(floor({w}), {self.top}) AS BIGINT)"

    def sql_value(self, i):
        return f"CAST({i} AS DOUBLE)"


class GeometricLadder(Ladder):
    """v_l = v1 (1 + eps)**(l - 1), up to the first level that is not below vmax."""

    def __init__(self, v1: float, eps: float, vmax: float):
        self.v1, self.ratio = float(v1), 1.0 + eps
        self.eps = eps
        self.top = max(1, math.ceil(math.log(vmax / v1) / math.log1p(eps) - 1e-12) + 1)

    def value(self, i):
        return F.when(i <= 0, F.lit(0.0)).otherwise(F.lit(self.v1) * F.pow(F.lit(self.ratio), i - 1))

    def index(self, w):
        guess = F.greatest(F.lit(0), F.least(F.lit(self.top), F.floor(F.log(w / self.v1) / math.log(self.ratio)) + 1)).cast("long")
        down = F.when(self.value(guess) > w, guess - 1).otherwise(guess)  # the logarithm may be off by one step
        up = F.when((down < self.top) & (self.value(down + 1) <= w), down + 1).otherwise(down)
        return F.when(w < self.v1, F.lit(0)).otherwise(up).cast("long")

    def np_value(self, i):
        i = np.asarray(i)
        return np.where(i <= 0, 0.0, self.v1 * np.power(self.ratio, i.astype(float) - 1))

    def np_index(self, w):
        w = np.asarray(w, float)
        guess = np.clip(np.floor(np.log(np.maximum(w, 1e-300) / self.v1) / math.log(self.ratio)) + 1, 0, self.top).astype(np.int64)
        guess -= self.np_value(guess) > w
        guess += (guess < self.top) & (self.np_value(guess + 1) <= w)
        return np.where(w < self.v1, 0, guess)

    def sql_value(self, i):
        return f"(CASE WHEN {i} <= 0 THEN 0.0 ELSE {self.v1!r} * pow({self.ratio!r}, {i} - 1) END)"

    def sql_index(self, w):
        guess = f"CAST(greatest(0, least({self.top}, floor(ln({w} / {self.v1!r}) / {math.log(self.ratio)!r}) + 1)) AS BIGINT)"
        down = f"({guess} - (CASE WHEN {self.sql_value(guess)} > {w} THEN 1 ELSE 0 END))"
        return f"(CASE WHEN {w} < {self.v1!r} THEN 0 ELSE {down} + (CASE WHEN {down} < {self.top} AND {self.sql_value(f'({down} + 1)')} <= {w} THEN 1 ELSE 0 END) END)"


class ListLadder(Ladder):
    """Any ascending list of levels, of bounded length (it goes with the plan)."""

    def __init__(self, values: list[float]):
        self.values = [0.0, *map(float, values)]
        if any(a >= b for a, b in zip(self.values, self.values[1:])):
            raise ValueError("levels must ascend from above 0")
        self.top = len(self.values) - 1

    def _array(self) -> Column:
        return F.array(*[F.lit(v) for v in self.values])

    def index(self, w):
        return (F.size(F.filter(self._array(), lambda v: v <= w)) - 1).cast("long")

    def value(self, i):
        return F.element_at(self._array(), (i + 1).cast("int"))

    def np_index(self, w):
        return np.searchsorted(self.values, w, "right") - 1

    def np_value(self, i):
        return np.asarray(self.values)[i]

    def place(self, w: float) -> int:
        return bisect_right(self.values, w) - 1


class FloatLadder(Ladder):
    """All positive finite IEEE values of one width as levels: the level's index is the value's bit pattern.

    As columns, exponent and mantissa come from comparisons with exact powers of two, so both forms agree to the bit.
    """

    def __init__(self, bits: int = 32):
        self.bits = bits
        self.float, self.int = (np.float32, np.int32) if bits == 32 else (np.float64, np.int64)
        self.top = int(np.array(np.finfo(self.float).max, self.float).view(self.int))
        self.mantissa, self.bias = (23, 127) if bits == 32 else (52, 1023)

    def _two(self, e: Column) -> Column:
        """2**e, in two factors so that neither leaves the range of doubles."""
        half = F.floor(e / 2)
        return F.pow(F.lit(2.0), half) * F.pow(F.lit(2.0), e - half)

    def index(self, w):
        low, below, most = 1 - self.bias, 1 << self.mantissa, float(np.finfo(self.float).max)

        def placed(w, e):
            scaled = F.floor(w / self._two(F.floor(e / 2)) / self._two(e - F.floor(e / 2)) * F.lit(2.0**self.mantissa)).cast("long")
            # numbers under the smallest exponent have no leading one
            return _let(scaled, lambda k: F.when(k < F.lit(below), k).otherwise(F.shiftleft((e - low + 1).cast("long"), self.mantissa) + k - F.lit(below)))

        def of(w):
            guess = F.greatest(F.lit(low), F.least(F.lit(self.bias), F.floor(F.log2(w)))).cast("int")
            down = lambda g: F.when((g > low) & (self._two(g) > w), g - 1).otherwise(g)  # noqa: E731  (the logarithm may be off by one)
            up = lambda d: F.when((d < self.bias) & (self._two(d + 1) <= w), d + 1).otherwise(d)
            found = _let(guess, lambda g: _let(down(g), lambda d: _let(up(d), lambda e: placed(w, e))))
            return F.when(w <= 0, F.lit(0).cast("long")).when(w > most, F.raise_error(F.lit("weight too large for the ladder")).cast("long")).otherwise(found)

        return _let(w.cast("double"), of)

    def value(self, i):
        def of(i):
            e, m = F.shiftright(i, self.mantissa), i.bitwiseAND(F.lit((1 << self.mantissa) - 1)).cast("double")
            whole = F.when(e > 0, m + F.lit(2.0**self.mantissa)).otherwise(m)
            return whole * self._two(F.greatest(e, F.lit(1)) - F.lit(self.bias + self.mantissa))

        return _let(i.cast("long"), of)

    def np_index(self, w):
        w = np.asarray(w, float)
        if (w > float(np.finfo(self.float).max)).any():
            raise ValueError("weight too large for the ladder")
        near = w.astype(self.float)
        near = np.where(near.astype(float) > w, np.nextafter(near, self.float(0)), near).astype(self.float)  # round down
        return near.view(self.int).astype(np.int64)

    def np_value(self, i):
        return np.asarray(i, np.int64).astype(self.int).view(self.float).astype(float)


def discretize(bags: DataFrame, ladder: Ladder) -> DataFrame:
    """Adds level (index) and level_weight (rounded weight); elements below the first level go."""
    return bags.withColumn("level", ladder.index(F.col("weight"))).where("level >= 1").withColumn("level_weight", ladder.value(F.col("level")))


def rounding_bounds(j: Column, eps: float) -> tuple[Column, Column]:
    """Where the similarity of rounded weights can lie, given that of the weights."""
    return j / (1 + eps), j * (1 + eps)


def eps_negligible(j, m, eps, factor: float = 0.1):
    """Whether rounding is far below the estimate's own relative error, which has no bound at similarity 0."""
    if isinstance(j, Column):
        return F.when(j == 0, True).otherwise(eps < factor * F.sqrt((1 - j) / (F.nullif(j, F.lit(0.0)) * m)))
    return eps < factor * math.sqrt((1 - j) / (j * m))
