"""Word hashes in numpy: 64-bit hashes of all words of a buffer at once, and of stretches of words."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
#: The modulus of stretch hashes, a prime; and the two bases whose powers weigh a stretch's values.
PRIME = (1 << 61) - 1
_BASES = (0x19D1AC9B3E0A5C47, 0x0B3F27C4D8E6195B)
#: Bytes that are worked on at once.
BLOCK = 1 << 20
#: The separators of the plain word rule: space and bytes 9 to 13.
SEPARATOR = np.zeros(256, bool)
SEPARATOR[[32, 9, 10, 11, 12, 13]] = True


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit values (the finaliser of splitmix64)."""
    x = x + U(0x9E3779B97F4A7C15)
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


#: A random value for each byte at each of the first places of a word. Words are hashed by tables, as sums of powers modulo 2^64 agree for some pairs of texts whatever the base.
_PLACES = 64
_TABLE = mix(np.arange(1, _PLACES * 256 + 1, dtype=np.uint64) * U(0xA0761D6478BD642F))
_P, _LOW32, _LOW29, _LOW30, _LOW31 = U(PRIME), U((1 << 32) - 1), U((1 << 29) - 1), U((1 << 30) - 1), U((1 << 31) - 1)


def _reduce(x: np.ndarray) -> np.ndarray:
    x = (x & _P) + (x >> U(61))
    return np.where(x >= _P, x - _P, x)


def times(a: np.ndarray, b: np.ndarray | np.uint64) -> np.ndarray:
    """The product modulo PRIME of numbers below it, by halves of 32 bits."""
    a1, a0, b1, b0 = a >> U(32), a & _LOW32, b >> U(32), b & _LOW32
    middle, low = a1 * b0 + a0 * b1, a0 * b0
    return _reduce(((a1 * b1) << U(3)) + (middle >> U(29)) + ((middle & _LOW29) << U(32)) + (low & _P) + (low >> U(61)))


class Powers:
    """Powers of a base and of its inverse, modulo PRIME, as far as they were asked for."""

    def __init__(self, base: int):
        self.base, self.inverse = base, pow(base, -1, PRIME)
        self.up = self.down = np.ones(1, np.uint64)

    def __call__(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        while len(self.up) < n:
            k = len(self.up)
            self.up = np.concatenate([self.up, times(self.up, U(pow(self.base, k, PRIME)))])
            self.down = np.concatenate([self.down, times(self.down, U(pow(self.inverse, k, PRIME)))])
        return self.up[:n], self.down[:n]


#: Two independent families of stretch hashes; together they have some 120 bits.
WORDS, MORE = (Powers(b) for b in _BASES)


def stretch_sums(values: np.ndarray, powers: Powers) -> np.ndarray:
    """Prefix sums, modulo PRIME, of the values times the powers. For up to 2^30 values."""
    up, _ = powers(len(values))
    x = times(_reduce(values), up)
    low, high = np.cumsum(x & _LOW30, dtype=np.uint64), np.cumsum(x >> U(30), dtype=np.uint64)
    out = np.zeros(len(values) + 1, np.uint64)
    out[1:] = _reduce(low + (high >> U(31)) + ((high & _LOW31) << U(30)))
    return out


def stretch_hash(sums: np.ndarray, start: np.ndarray, end: np.ndarray, powers: Powers) -> np.ndarray:
    """The hash of values[start:end], wherever it stands."""
    _, down = powers(len(sums))
    return mix(times(_reduce(sums[end] + (_P - sums[start])), down[start]) + (end - start).astype(np.uint64) * U(0xC2B2AE3D27D4EB4F))


def word_spans(data: np.ndarray, separator: np.ndarray = SEPARATOR) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the words of a buffer of bytes."""
    gap = np.ones(len(data) + 2, bool)
    gap[1:-1] = separator[data]
    edge = np.flatnonzero(gap[1:] != gap[:-1])
    return edge[::2], edge[1::2]


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A hash of each word, the same wherever it stands; a megabyte at a time."""
    out = np.empty(len(starts), np.uint64)
    i = 0
    while i < len(starts):
        j = max(i + 1, int(np.searchsorted(ends, starts[i] + BLOCK, "right")))
        lo, hi = int(starts[i]), int(ends[j - 1])
        begin = (starts[i:j] - lo).astype(np.int64)
        size = (ends[i:j] - starts[i:j]).astype(np.uint64)
        place = np.arange(hi - lo, dtype=np.int64) - np.repeat(begin, np.diff(np.append(begin, hi - lo)))
        values = np.zeros(hi - lo + 1, np.uint64)
        values[:-1] = _TABLE[((place & (_PLACES - 1)) << 8) | data[lo:hi]]
        if len(far := np.flatnonzero(place >= _PLACES)):
            values[far] = mix(values[far] ^ mix((place[far] // _PLACES).astype(np.uint64)))
        pairs = np.stack([begin, (ends[i:j] - lo).astype(np.int64)], 1).reshape(-1)
        out[i:j] = mix(np.add.reduceat(values, pairs)[::2] + size * U(0xC2B2AE3D27D4EB4F))
        i = j
    return out


def grouped(texts: Iterable[bytes], most: int = BLOCK) -> Iterator[tuple[int, list[bytes]]]:
    """Runs of texts of about a megabyte, each with the index of its first."""
    at, now, n, i = 0, [], 0, -1
    for i, t in enumerate(texts):
        now.append(t)
        n += len(t) + 1
        if n >= most:
            yield at, now
            at, now, n = i + 1, [], 0
    if now:
        yield at, now


def grouped_column(column: pa.Array, most: int = BLOCK) -> Iterator[tuple[int, list[bytes]]]:
    """Runs of a text column's values (null: empty), as UTF-8, of about a megabyte, each with the index of its first. Only one run at a time is copied."""
    size = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64) + 1
    ends, at = np.cumsum(size), 0
    while at < len(column):
        before = int(ends[at - 1]) if at else 0
        to = max(at + 1, int(np.searchsorted(ends, before + most, "right")))
        yield at, [t or b"" for t in column.slice(at, to - at).cast(pa.binary()).to_pylist()]
        at = to
