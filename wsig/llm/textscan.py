"""Words, lines and rolling hashes of whole Arrow text columns, in numpy.

A word is a run of bytes other than space and ``\\t \\n \\v \\f \\r``; UTF-8 lets this be decided byte by byte.
Hashes of byte runs and of word runs are differences of prefix sums of ``value * base**index`` modulo 2**64,
brought back to index 0 by the inverse power and mixed at the end.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text that one numpy step works on; a longer document is a step of its own, hashed in pieces of this size.
STEP = 1 << 20
_BASES = (0x9E3779B97F4A7C15, 0xD1342543DE82EF95)
_U = np.uint64
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_powers: dict[tuple[int, bool], np.ndarray] = {}
try:  # a C library other than glibc has none
    _trim = ctypes.CDLL(None).malloc_trim
except (AttributeError, OSError, TypeError):
    _trim = None


def powers(seed: int, n: int, inverse: bool = False) -> np.ndarray:
    """base**i (or its inverse) for i < n, kept between calls."""
    have = _powers.get((seed, inverse))
    if have is None or len(have) < n:
        base = pow(_BASES[seed], -1, 1 << 64) if inverse else _BASES[seed]
        steps = np.full(max(n, 1 << 16), base, _U)
        steps[0] = 1
        have = _powers[seed, inverse] = np.multiply.accumulate(steps)
    return have[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64 bits that spreads each bit over all."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x ^= x >> _U(27)
    x *= _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def run_sums(values: np.ndarray, seed: int) -> np.ndarray:
    """Prefix sums whose differences are hashes of runs of values."""
    out = np.zeros(len(values) + 1, _U)
    np.cumsum(values * powers(seed, len(values)), out=out[1:])
    return out


def run_hash(sums: np.ndarray, starts: np.ndarray, ends: np.ndarray, seed: int) -> np.ndarray:
    """Hash of values[starts:ends], the same wherever the run stands."""
    return mix((sums[ends] - sums[starts]) * powers(seed, len(sums), True)[starts] + (ends - starts).astype(_U))


def as_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All documents' bytes on end, and len(column) + 1 offsets; a null is an empty document."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_binary())
    if column.null_count:
        column = column.fill_null(b"")
    n, at = len(column), column.offset
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(column.buffers()[1], np.int64)[at : at + n + 1]
    data = column.buffers()[2]
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def steps(batches: Iterator[pa.RecordBatch], text: str = "text", size: int = STEP) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of about ``size`` bytes of text, so that memory doesn't depend on Spark's batch size.

    At the end of a task freed memory goes back to the system: workers are kept, and what one stage frees the next stage's JVM can use.
    """
    try:
        yield from _steps(batches, text, size)
    finally:
        give_back()


def give_back() -> None:
    """Returns memory that Arrow's pool and the C library hold but do not use."""
    pa.default_memory_pool().release_unused()
    if _trim is not None:
        _trim(0)


def _steps(batches: Iterator[pa.RecordBatch], text: str, size: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        if batch.num_rows == 0:
            continue
        lengths = pc.fill_null(pc.binary_length(batch.column(batch.schema.get_field_index(text))), 0)
        offsets = np.concatenate(([0], np.cumsum(lengths.to_numpy(zero_copy_only=False), dtype=np.int64)))
        i = 0
        while i < batch.num_rows:
            j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + size, "right")) - 1)
            yield batch.slice(i, j - i)
            i = j


class Scan:
    """Words of a column of texts."""

    def __init__(self, column: pa.Array | None, parts: tuple[np.ndarray, np.ndarray] | None = None):
        self.bytes, self.offsets = as_bytes(column) if parts is None else parts
        solid = ~_SPACE[self.bytes]
        n = len(solid)
        before = np.zeros(n, bool)
        before[1:] = solid[:-1]
        firsts = self.offsets[:-1]
        before[firsts[firsts < n]] = False
        after = np.zeros(n, bool)
        after[:-1] = solid[1:]
        lasts = self.offsets[1:]
        after[lasts[lasts > 0] - 1] = False
        self.starts = np.flatnonzero(solid & ~before)
        self.ends = np.flatnonzero(solid & ~after) + 1
        self.first_word = np.searchsorted(self.starts, self.offsets)
        self.n_words = np.diff(self.first_word)
        self.doc = np.repeat(np.arange(len(self.n_words)), self.n_words)
        self.solid = solid

    def per_doc(self, flags: np.ndarray) -> np.ndarray:
        """Sum of a value for each byte, by document."""
        sums = np.zeros(len(flags) + 1, np.int64)
        np.cumsum(flags, out=sums[1:])
        return np.diff(sums[self.offsets])

    def words_per_doc(self, flags: np.ndarray) -> np.ndarray:
        """Sum of a value for each word, by document."""
        sums = np.zeros(len(flags) + 1, np.int64)
        np.cumsum(flags, out=sums[1:])
        return np.diff(sums[self.first_word])

    def hash_runs(self, starts: np.ndarray, ends: np.ndarray, seed: int = 0) -> np.ndarray:
        """Hash of each byte run; runs ascend. Works in pieces, so a long document takes no more memory than a short one."""
        out = np.empty(len(starts), _U)
        i = 0
        while i < len(starts):
            j = max(i + 1, int(np.searchsorted(ends, starts[i] + STEP, "right")))
            at = starts[i]
            sums = run_sums(self.bytes[at : ends[j - 1]].astype(_U) + _U(1), seed)
            out[i:j] = run_hash(sums, starts[i:j] - at, ends[i:j] - at, seed)
            i = j
        return out

    def word_hash(self, seed: int = 0) -> np.ndarray:
        return self.hash_runs(self.starts, self.ends, seed)

    def window_starts(self, k: int) -> np.ndarray:
        """Words from which k words of one document follow."""
        n = len(self.doc)
        if n < k:
            return np.zeros(0, np.int64)
        return np.flatnonzero(self.doc[k - 1 :] == self.doc[: n - k + 1])


def windows(values: np.ndarray, starts: np.ndarray, k: int, seed: int = 0) -> np.ndarray:
    """Hash of each window of k values that begins at starts."""
    return run_hash(run_sums(values, seed), starts, starts + k, seed)
