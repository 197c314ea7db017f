"""Counter-based randomness: every draw is a hash of its key, so it needs no state, order or seed chain.

``xxhash64`` is the fast kind, with a numpy twin that gives the same bits; ``md5`` can be evaluated by other SQL engines.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: What a draw is for; part of its key.
FIRST, SIDE, COMPONENT, NEXT, U1, U2, U3, U4, U5, U6, U7 = range(1, 12)

_P = [np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5)]


def _rotl(x: np.ndarray, r: int) -> np.ndarray:
    return (x << np.uint64(r)) | (x >> np.uint64(64 - r))


def np_hash(*keys, seed=42) -> np.ndarray:
    """Spark's xxhash64 over columns of longs, in numpy; with the hash of the first keys as ``seed`` it goes on with further ones."""
    with np.errstate(over="ignore"):
        h = np.asarray(seed, np.uint64)
        for k in keys:
            h = np.asarray(h, np.uint64) + _P[4] + np.uint64(8)
            h = h ^ (_rotl(np.asarray(k).astype(np.int64).view(np.uint64) * _P[1], 31) * _P[0])
            h = _rotl(h, 27) * _P[0] + _P[3]
            h = (h ^ (h >> np.uint64(33))) * _P[1]
            h = (h ^ (h >> np.uint64(29))) * _P[2]
            h = h ^ (h >> np.uint64(32))
        return h


def np_u01(*keys, seed=42) -> np.ndarray:
    return ((np_hash(*keys, seed=seed) >> np.uint64(11)).astype(np.float64) + 0.5) / 2.0**53


def bernoulli_bits(p: float, bits: int) -> tuple[bool, int]:
    """Whether a uniform number with the given 64 binary digits lies under p, and how many digits that took: two on average."""
    for used in range(1, 65):
        p *= 2
        digit, own = bits >> (64 - used) & 1, int(p >= 1)
        p -= own
        if digit != own:
            return digit < own, used
        if p == 0:  # the rest of p's digits are zeros, so the number isn't under it
            return False, used
    return False, 64


def _halves() -> np.ndarray:
    """Sums of ln(2)**k / k! for k = 1, 2, ...: chances of an exponential's part under ln 2."""
    term, out = 1.0, []
    for k in range(1, 20):
        term *= np.log(2) / k
        out.append((out[-1] if out else 0.0) + term)
    return np.array(out)


_PARTS = _halves()


def np_exponential(*keys) -> np.ndarray:
    """Exponential draws without a logarithm: whole multiples of ln 2 from the leading ones of a keyed word, and the least of a few uniforms."""
    word = np_hash(*keys, 0)
    ones = np.zeros(word.shape, np.int64)
    rest = word.copy()
    running = np.ones(word.shape, bool)
    for _ in range(64):
        running = running & (rest >> np.uint64(63) == np.uint64(1))
        if not running.any():
            break
        ones += running
        rest = np.where(running, rest << np.uint64(1), rest)
    u = np_u01(*keys, 1)
    many = np.searchsorted(_PARTS, u, "right") + 1
    least = np_u01(*keys, 2)
    for k in range(2, int(many.max(initial=1)) + 1):
        least = np.where(k <= many, np.minimum(least, np_u01(*keys, k + 1)), least)
    return np.log(2) * (ones + np.where(u < np.log(2), u / np.log(2), least))


class Prng:
    """Keyed uniform draws as columns."""

    def __init__(self, kind: str = "xxhash64", salt: int = 0):
        if kind not in ("xxhash64", "md5"):
            raise ValueError(f"unknown kind {kind}")
        self.kind, self.salt = kind, salt

    def _key(self, keys) -> list[Column]:
        as_column = lambda k: k if isinstance(k, Column) else F.col(k) if isinstance(k, str) else F.lit(k)
        return [as_column(k).cast("long") for k in (self.salt, *keys)]

    def u01(self, *keys) -> Column:
        """Uniform in (0, 1), never 0 or 1."""
        keys = self._key(keys)
        if self.kind == "md5":
            word = F.conv(F.substring(F.md5(F.concat_ws("|", *keys).cast("binary")), 1, 12), 16, 10).cast("long")
            return (word + F.lit(0.5)) / F.lit(2.0**48)
        return (F.shiftrightunsigned(F.xxhash64(*keys), 11) + F.lit(0.5)) / F.lit(2.0**53)

    def identity(self, *keys) -> Column:
        """What makes a draw recognisable: a long, or the key's text where other engines must agree."""
        keys = self._key(keys)
        return F.concat_ws("|", *keys) if self.kind == "md5" else F.xxhash64(*keys)

    def exponential(self, rate: Column, *keys) -> Column:
        return -F.log(self.u01(*keys)) / rate

    def uniform_int(self, n: int, *keys) -> Column:
        """Uniform in 0 .. n - 1."""
        return F.least(F.floor(self.u01(*keys) * n), F.lit(n - 1)).cast("int")

    def bernoulli(self, p: Column, *keys) -> Column:
        return self.u01(*keys) < p


def sql_u01(*keys: str, salt: int = 0) -> str:
    """The md5 kind as DuckDB SQL over expressions of integer type."""
    text = ", ".join(f"CAST({k} AS BIGINT)" for k in (str(salt), *keys))
    return f"((('0x' || substr(md5(concat_ws('|', {text})), 1, 12))::BIGINT + 0.5) / 281474976710656.0)"
