"""Vectorised text handling over Arrow string columns: words, hashes and windows as numpy arrays.

Texts are read as UTF-8 bytes straight from Arrow buffers. A null text counts as an empty one. Arrays cover a
slice of a batch whose bytes are bounded, so memory doesn't depend on how many rows Spark puts in a batch; a
single longer text makes a slice by itself and is never cut. Its words are hashed piece by piece (`hashes_of`), so what
stands for a whole text are a few masks of a byte per byte and arrays of 8 bytes per word: some 20 bytes per byte of text.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa

SLICE_BYTES = 1 << 20

#: Odd multipliers of 64-bit mixing.
MIX_A = np.uint64(0xBF58476D1CE4E5B9)
MIX_B = np.uint64(0x94D049BB133111EB)
GOLDEN = np.uint64(0x9E3779B97F4A7C15)
BASE = 0x5851F42D4C957F2D

#: Word separators: space and the control characters from tab to carriage return.
NOT_SPACE = np.ones(256, dtype=bool)
NOT_SPACE[[0x20, *range(0x09, 0x0E)]] = False

LOWER = np.arange(256, dtype=np.uint8)
LOWER[ord("A") : ord("Z") + 1] += 32


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every input bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * MIX_A
    x ^= x >> np.uint64(27)
    x *= MIX_B
    x ^= x >> np.uint64(31)
    return x


@lru_cache(maxsize=1)
def _byte_values() -> np.ndarray:
    return mix((np.arange(256, dtype=np.uint64) + np.uint64(1)) * GOLDEN)


_powers: dict[str, np.ndarray] = {}


def _power_table(n: int) -> tuple[np.ndarray, np.ndarray]:
    """base^j and base^-j modulo 2^64 for j up to n."""
    if "up" not in _powers or len(_powers["up"]) <= n:
        size = max(n + 1, SLICE_BYTES + 1)
        for name, base in (("up", BASE), ("down", pow(BASE, -1, 1 << 64))):
            steps = np.full(size, base, dtype=np.uint64)
            steps[0] = 1
            _powers[name] = np.cumprod(steps, dtype=np.uint64)
    return _powers["up"], _powers["down"]


def column_bytes(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of an Arrow string or binary array; nulls are empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if col.null_count:
        col = col.fill_null(b"" if pa.types.is_binary(col.type) or pa.types.is_large_binary(col.type) else "")
    wide = pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type)
    _, offs, data = col.buffers()
    if not len(col):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(offs, np.int64 if wide else np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(col: pa.Array, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, row after the last, bytes, offsets) with at most limit bytes unless one text is longer."""
    data, offsets = column_bytes(col)
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + limit, "right")) - 1)
        yield lo, hi, data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
        lo = hi


def runs_of(inside: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of maximal runs of true bytes, none across a border of offsets."""
    if not len(inside):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    first, last = inside.copy(), inside.copy()
    first[1:] &= ~inside[:-1]
    last[:-1] &= ~inside[1:]
    full = offsets[1:] > offsets[:-1]
    a, z = offsets[:-1][full], offsets[1:][full] - 1
    first[a], last[z] = inside[a], inside[z]
    return np.flatnonzero(first), np.flatnonzero(last) + 1


def words_of(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of words, and for each text where its words begin (one more entry than texts)."""
    s, e = runs_of(NOT_SPACE[data], offsets)
    return s, e, np.searchsorted(s, offsets, "left")


class RangeHash:
    """64-bit hashes of any byte ranges of data, each in constant time: prefix sums of random byte values times
    powers of an odd base; equal bytes give equal hashes wherever they stand."""

    def __init__(self, data: np.ndarray):
        up, self.down = _power_table(len(data))
        self.sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(_byte_values()[data] * up[: len(data)], out=self.sums[1:])

    def of(self, s: np.ndarray, e: np.ndarray) -> np.ndarray:
        return mix((self.sums[e] - self.sums[s]) * self.down[s] + (e - s).astype(np.uint64) * GOLDEN)


def hashes_of(data: np.ndarray, s: np.ndarray, e: np.ndarray, limit: int = 4 * SLICE_BYTES) -> np.ndarray:
    """RangeHash of sorted, disjoint ranges, at most `limit` bytes of data at a time unless one range is longer."""
    if len(data) <= limit:
        return RangeHash(data).of(s, e)
    out, i = np.empty(len(s), np.uint64), 0
    while i < len(s):
        j = max(i + 1, int(np.searchsorted(e, s[i] + limit, "right")))
        out[i:j] = RangeHash(data[s[i] : e[j - 1]]).of(s[i:j] - s[i], e[i:j] - s[i])
        i = j
    return out


def sequence_hash(h: np.ndarray, begin: np.ndarray, n: int) -> np.ndarray:
    """Hash of the n entries of h from each begin, and of n itself."""
    v = h[begin]
    for j in range(1, n):
        v = mix(v * GOLDEN + h[begin + j])
    return mix(v + np.uint64(n))


def ngrams(h: np.ndarray, n: int) -> np.ndarray:
    """Hash of each n consecutive entries of h (len(h) - n + 1 of them, or none)."""
    m = len(h) - n + 1
    if m <= 0:
        return np.zeros(0, np.uint64)
    out = h[:m] * GOLDEN
    for k in range(1, n):
        out = mix(out + h[k : k + m]) * GOLDEN
    return mix(out)


def within(word_first: np.ndarray, n: int, total: int) -> tuple[np.ndarray, np.ndarray]:
    """Of the total windows of n words over a slice, the mask of those that stay in one text, and the text of
    each window. word_first: where each text's words begin."""
    m = max(0, total - n + 1)
    doc = np.repeat(np.arange(len(word_first) - 1), np.diff(word_first))
    return (doc[:m] == doc[n - 1 : n - 1 + m]) if m else np.zeros(0, bool), doc[:m]


def sums_by(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Sum of values over each [first[i], first[i + 1])."""
    total = np.concatenate([np.zeros((1, *values.shape[1:]), values.dtype), np.cumsum(values, axis=0)])
    return total[first[1:]] - total[first[:-1]]
