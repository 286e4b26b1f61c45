"""Words of Arrow text columns as numpy offsets and 64-bit hashes, a few megabytes of text at a time."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

#: Bytes of text per step; temporaries take about thirty times as much. A longer document is a step of its own, of which as
#: many bytes at a time are hashed; then a few bytes per byte of text are held.
STEP_BYTES = 1 << 19

SPACES = np.zeros(256, bool)
SPACES[[0x20, *range(0x09, 0x0E)]] = True
#: Words of everything but ASCII white space, as `[^\x20\x09-\x0D]+`.
GRAPHIC = ~SPACES
#: Words of a-z, 0-9 and everything beyond ASCII.
ALNUM = np.zeros(256, bool)
ALNUM[[*range(0x30, 0x3A), *range(0x61, 0x7B), *range(0x80, 0x100)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32
SAME = np.arange(256, dtype=np.uint8)

_BASE = 0x9E3779B97F4A7C15 | 1
_GRAM = 0xD6E8FEB86659FD93 | 1
_TABLE = np.random.default_rng(20240607).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_powers: dict[int, np.ndarray] = {}
_LOW = 16


def _power(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1), modulo 2**64."""
    have = _powers.get(base)
    if have is None or len(have) < n:
        have = np.full(max(n, 1 << _LOW), base, np.uint64)
        have[0] = 1
        have = _powers[base] = np.multiply.accumulate(have)
    return have[:n]


def _raised(base: int, exponents: np.ndarray) -> np.ndarray:
    """base**e modulo 2**64 for each e, by two small tables."""
    low = _power(base, 1 << _LOW)[exponents & ((1 << _LOW) - 1)]
    far = int(exponents.max(initial=0)) >> _LOW
    return low if not far else low * _power(pow(base, 1 << _LOW, 1 << 64), far + 1)[exponents >> _LOW]


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1), from a table that is kept unless it were a long one."""
    return _power(base, n) if n <= 1 << 21 else _raised(base, np.arange(n))


def mix(x: np.ndarray) -> np.ndarray:
    """Spreads all bits over all bits (one to one)."""
    x = x ^ (x >> np.uint64(33))
    x *= np.uint64(0xFF51AFD7ED558CCD)
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xC4CEB9FE1A85EC53)
    x ^= x >> np.uint64(33)
    return x


def _sums(value, size: int, places: np.ndarray, base: int) -> np.ndarray:
    """At each place: the sum of value[i] * base**i over all i before it. value(a, b) gives values a .. b-1; places ascend."""
    found, carry = np.empty(len(places), np.uint64), np.uint64(0)
    for a in range(0, max(size, 1), STEP_BYTES):
        b = min(size, a + STEP_BYTES)
        run = np.zeros(b - a + 1, np.uint64)
        np.cumsum(value(a, b) * _power(base, b - a), out=run[1:])
        if a:
            run = run * np.uint64(pow(base, a, 1 << 64)) + carry
        i, j = np.searchsorted(places, a), np.searchsorted(places, b, "right")
        found[i:j] = run[places[i:j] - a]
        carry = run[-1]
    return found


def _hashed(before: np.ndarray, after: np.ndarray, starts: np.ndarray, ends: np.ndarray, base: int) -> np.ndarray:
    return mix((after - before) * _raised(pow(base, -1, 1 << 64), starts) + (ends - starts).astype(np.uint64))


def _spans(values: np.ndarray, starts: np.ndarray, ends: np.ndarray, base: int) -> np.ndarray:
    """Polynomial hashes of values[start:end], which don't depend on the place."""
    sums = np.zeros(len(values) + 1, np.uint64)
    np.cumsum(values * powers(base, len(values)), out=sums[1:])
    return _hashed(sums[starts], sums[ends], starts, ends, base)


@dataclass
class Words:
    """Words of documents `first` .. `first + len(offsets) - 2` of a batch; document i has words offsets[i]:offsets[i+1]."""

    first: int
    data: np.ndarray
    bounds: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    offsets: np.ndarray
    hashes: np.ndarray

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.offsets)

    def owner(self) -> np.ndarray:
        """The document of each word, counted from `first`."""
        return np.repeat(np.arange(len(self.offsets) - 1), self.counts)

    def grams(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Places of all runs of n words within one document, and their hashes."""
        if len(self.hashes) < n:
            return np.zeros(0, np.int64), np.zeros(0, np.uint64)
        at = np.arange(len(self.hashes) - n + 1)
        at = at[at + n <= np.repeat(self.offsets[1:], self.counts)[: len(at)]]
        return at, _spans(self.hashes, at, at + n, _GRAM)

    def spans(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Hashes of any runs of words, as grams() has them."""
        return _spans(self.hashes, starts, ends, _GRAM)


def buffers(column) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a text column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.fill_null("").cast(pa.large_string())
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    return (np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)), offsets


def steps(offsets: np.ndarray, size: int = STEP_BYTES) -> Iterator[tuple[int, int]]:
    """Runs of whole documents of about `size` bytes."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + size, "right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


def words(column, letters: np.ndarray = GRAPHIC, case: np.ndarray = SAME) -> Iterator[Words]:
    """Words of every document of a text column, with `case` applied to each byte first."""
    data, offsets = buffers(column)
    letters, table = letters[case], _TABLE[case]
    for i, j in steps(offsets):
        lo, hi = offsets[i], offsets[j]
        own, bounds = data[lo:hi], offsets[i : j + 1] - lo
        inside = np.zeros(len(own) + 2, bool)
        inside[1:-1] = letters[own]
        cut = np.zeros(len(own) + 1, bool)
        cut[bounds] = True
        starts = np.flatnonzero(inside[1:] & (~inside[:-1] | cut))
        ends = np.flatnonzero(inside[:-1] & (~inside[1:] | cut))
        value = lambda a, b, own=own: table[own[a:b]]
        hashes = _hashed(_sums(value, len(own), starts, _BASE), _sums(value, len(own), ends, _BASE), starts, ends, _BASE) if len(own) > STEP_BYTES else _spans(table[own], starts, ends, _BASE)
        yield Words(i, own, bounds, starts, ends, np.searchsorted(starts, bounds), hashes)
