"""Estimates from signatures, b-bit reduction and closed forms of error and cost."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

_as = lambda c: F.col(c) if isinstance(c, str) else c


def estimate_jaccard(a, b) -> Column:
    """Share of equal components of two signature arrays; null components (empty bags) never match."""
    a, b = _as(a), _as(b)
    same = F.aggregate(F.zip_with(a, b, lambda x, y: F.coalesce((x == y).cast("int"), F.lit(0))), F.lit(0), lambda s, x: s + x)
    empty = lambda x: F.forall(x, lambda v: v.isNull())
    return F.when(empty(a) & empty(b), F.lit(None)).otherwise(same / F.size(a))


def bbit(sig, bits: int) -> Column:
    """Each component reduced to ``bits`` bits by a hash keyed with its value."""
    mask = (1 << bits) - 1
    return F.transform(_as(sig), lambda h: F.xxhash64(h).bitwiseAND(F.lit(mask)).cast("int"))


def bbit_pack(sig, bits: int) -> Column:
    """b-bit components as binary, most significant bit first, padded with zeros to whole bytes."""
    text = F.array_join(F.transform(bbit(sig, bits), lambda v: F.lpad(F.bin(v), bits, "0")), "")
    n = F.ceil(F.length(text) / 8).cast("int")
    padded = F.rpad(text, n * 8, "0")
    bytes_ = F.transform(F.sequence(F.lit(0), n - 1), lambda i: F.lpad(F.conv(F.substr(padded, i * 8 + 1, F.lit(8)), 2, 16), 2, "0"))
    return F.unhex(F.array_join(bytes_, ""))


def without_chance(share, bits: int) -> Column:
    """A match share of b-bit components, freed of chance matches."""
    chance = 2.0**-bits
    return (share - chance) / (1 - chance)


def estimate_jaccard_bbit(a, b, bits: int, clip: bool = False) -> Column:
    """The match share of b-bit signatures, freed of chance matches."""
    raw = without_chance(estimate_jaccard(a, b), bits)
    return F.greatest(F.lit(0.0), F.least(F.lit(1.0), raw)) if clip else raw


def estimate_total_weight(h) -> Column:
    """Unbiased total weight of a bag from its m minima, each exponential with rate total / m."""
    h = _as(h)
    m = F.size(h)
    return m * (m - 1) / F.aggregate(h, F.lit(0.0), lambda s, x: s + x)


def estimator_variance(j, m: int, bits: int | None = None):
    """J(1-J)/m and, for b-bit signatures, what chance matches add."""
    base = j * (1 - j) / m
    return base if bits is None else base + (1 - j) / ((2**bits - 1) * m)


def expected_mse(j, m):
    return j * (1 - j) / m


def var_mse(j, m, n):
    """Variance of the mean squared error of n estimates from binomial match counts."""
    q = j * (1 - j)
    return q * q * (2 - 6 / m) / (m * m * n) + q / (m * m * m * n)


def zscore(mse, j, m, n):
    return (mse - expected_mse(j, m)) / (F.sqrt(var_mse(j, m, n)) if isinstance(mse, Column) else math.sqrt(var_mse(j, m, n)))


def harmonic(m: int) -> float:
    return sum(1 / i for i in range(1, m + 1))


def expected_points(m: int, i):
    """Bound on the points drawn for the i-th element of a set in random order."""
    if isinstance(i, Column):
        return F.when(i == 1, F.lit(m * harmonic(m))).otherwise(1 + F.lit(m * harmonic(m)) / i)
    return m * harmonic(m) if i == 1 else 1 + m * harmonic(m) / i


def signature_bytes(m: int, bits: int = 64) -> int:
    return -(-m * bits // 8)


def collision_probability(j, bands: int, rows: int):
    """The chance that banding makes a pair a candidate."""
    return 1 - (1 - j**rows) ** bands


def plan_bands(m: int, tau: float) -> tuple[int, int]:
    """Bands and rows of m components whose collision curve is steepest nearest to tau, not above it."""
    options = [(m // r, r) for r in range(1, m + 1) if m % r == 0]
    steep = [(abs((1 / b) ** (1 / r) - tau), b, r) for b, r in options if (1 / b) ** (1 / r) <= tau] or [(0.0, m, 1)]
    _, b, r = min(steep)
    return b, r


def bands_for_recall(m: int, tau: float, recall: float = 0.999) -> tuple[int, int]:
    """Bands and rows with the fewest false candidates that still find a pair of similarity tau with chance ``recall``."""
    options = [(m // r, r) for r in range(m, 0, -1) if collision_probability(tau, m // r, r) >= recall]
    return options[0] if options else (m, 1)
