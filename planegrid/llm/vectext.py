"""Words, word hashes and window hashes of whole Arrow text columns, without a Python object per word.

A word is a maximal run of bytes other than space and \\t \\n \\v \\f \\r; these are single bytes in UTF-8, so
bytes and code points give the same words. Hashes are polynomials over 2**64 with fixed odd bases, taken from
prefix sums (Rabin-Karp), then mixed. Such polynomials agree on some pairs of sequences of a thousand symbols or
more, whatever the base (Thue-Morse sequences), so they serve only for short runs: longer words and whole rows
have a cryptographic digest instead. Two families of hashes with bases of their own are independent.
"""

from __future__ import annotations

from dataclasses import dataclass
from hashlib import blake2b

import numpy as np
import pyarrow as pa

U = np.uint64
#: Fixed odd bases; BASE over the bytes of a word, STEP over the words of a window.
BASE, STEP = (U(0x9E3779B97F4A7C15), U(0xC2B2AE3D27D4EB4F)), (U(0xD6E8FEB86659FD93), U(0x9FB21C651E98DF25))
#: Symbols up to which a polynomial hash is trusted.
SHORT = 256
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def inverse(odd: int) -> int:
    return pow(int(odd), -1, 1 << 64)


_POWERS: dict[int, np.ndarray] = {}
#: Powers that are kept; more are worked out anew for the few texts that need them.
KEPT = 1 << 20


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**n modulo 2**64."""
    key = int(base)
    have = _POWERS.get(key)
    if have is None or len(have) <= n:
        out = np.full(max(n + 1, 1 << 16), U(key), dtype=np.uint64)
        out[0] = 1
        have = np.multiply.accumulate(out, out=out)
        if len(have) <= KEPT + (KEPT >> 2):
            _POWERS[key] = have
    return have[: n + 1]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection that spreads the low bits' entropy over all 64."""
    x = x ^ (x >> U(32))
    x = x * U(0xD6E8FEB86659FD93)
    x = x ^ (x >> U(32))
    x = x * U(0xD6E8FEB86659FD93)
    return x ^ (x >> U(32))


@dataclass
class Words:
    """start, end: byte places of every word in data; first: the first word of each row, with the total at the end."""

    data: np.ndarray
    start: np.ndarray
    end: np.ndarray
    first: np.ndarray

    def __len__(self) -> int:
        return len(self.first) - 1

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def hashes(self, family: int = 0) -> np.ndarray:
        """A hash of each word."""
        n, base = len(self.data), BASE[family]
        sums = np.zeros(n + 1, dtype=np.uint64)
        terms = sums[1:]
        np.add(self.data, U(1), out=terms, dtype=np.uint64)
        terms *= powers(base, n)[:n]
        np.cumsum(terms, out=terms)
        raw = sums[self.end] - sums[self.start]
        del sums, terms
        raw *= powers(inverse(base), n)[self.start]
        out = mix(raw + (self.end - self.start).astype(np.uint64) * U(0xA24BAED4963EE407))
        for k in np.flatnonzero(self.end - self.start > SHORT).tolist():
            out[k] = digest(self.data[self.start[k] : self.end[k]], family)[0]
        return out


def digest(data: np.ndarray, family: int = 0) -> tuple[int, int]:
    """128 bits of an array's bytes."""
    found = blake2b(np.ascontiguousarray(data).tobytes(), digest_size=16, salt=b"%d" % family).digest()
    return int.from_bytes(found[:8], "little"), int.from_bytes(found[8:], "little")


#: Besides white space, ASCII punctuation ends a word.
PLAIN = _SPACE.copy()
PLAIN[[b for b in range(128) if not chr(b).isalnum()]] = True


def words(column: pa.Array, lower: bool = False, space: np.ndarray = _SPACE) -> Words:
    """Of a string column; a null row has no words. space: flags of the bytes between words."""
    n = len(column)
    if column.null_count:
        column = column.fill_null("")
    big = pa.types.is_large_string(column.type)
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64 if big else np.int32, count=n + 1, offset=column.offset * (8 if big else 4)).astype(np.int64) if n else np.zeros(1, dtype=np.int64)
    raw = column.buffers()[2] if n else None
    data = np.frombuffer(raw, dtype=np.uint8)[offsets[0] : offsets[-1]] if raw is not None and raw.size else np.zeros(0, dtype=np.uint8)
    offsets = offsets - offsets[0]
    if lower:
        data = _LOWER[data]
    space = space[data]
    begins = np.ones(len(data), dtype=bool)
    if len(data):
        begins[1:] = space[:-1]
        begins[offsets[:-1][offsets[:-1] < len(data)]] = True
    begins &= ~space
    ends = np.ones(len(data), dtype=bool)
    if len(data):
        ends[:-1] = space[1:]
        ends[offsets[1:][offsets[1:] > 0] - 1] = True
    ends &= ~space
    start, end = np.flatnonzero(begins), np.flatnonzero(ends) + 1
    return Words(data, start, end, np.searchsorted(start, offsets))


def windows(values: np.ndarray, size: int, family: int = 0) -> np.ndarray:
    """A hash of every run of size values, by its first place; runs may cross rows, see starts()."""
    n = len(values)
    if n < size:
        return np.zeros(0, dtype=np.uint64)
    if size > SHORT:
        parts, out = windows(values, SHORT, family), np.zeros(n - size + 1, dtype=np.uint64)
        for at in (*range(0, size - SHORT, SHORT), size - SHORT):
            out = mix(out * STEP[family] + parts[at : at + len(out)])
        return out
    step = STEP[family]
    sums = np.zeros(n + 1, dtype=np.uint64)
    np.cumsum(values * powers(step, n)[:n], out=sums[1:])
    return mix((sums[size:] - sums[:-size]) * powers(inverse(step), n)[: n - size + 1])


def rows(values: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """128 bits of each row's whole run of values, as two arrays; a row without values has zeros."""
    bounds = first.tolist()
    found = [digest(values[a:b]) if b > a else (0, 0) for a, b in zip(bounds[:-1], bounds[1:])]
    both = np.array(found, dtype=np.uint64).reshape(-1, 2)
    return both[:, 0].copy(), both[:, 1].copy()


def starts(first: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Places at which a run of size values lies in one row, and the row of each."""
    counts = np.maximum(np.diff(first) - size + 1, 0)
    row = np.repeat(np.arange(len(counts)), counts)
    before = np.zeros(len(counts), dtype=np.int64)
    np.cumsum(counts[:-1], out=before[1:])
    return np.arange(len(row)) - before[row] + first[:-1][row], row
