"""Digit sequences packed into bit planes, and counting in their prefixes, as SQL expressions over built-in functions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def packed(digits: str, bits: int) -> Column:
    """digits: name of an array<bigint>. For each bit of a digit an array of 64-bit words, first entry in the lowest bit."""
    word = f"aggregate(sequence(0, least(63, size({digits}) - 1 - i * 64)), 0L, (a, p) -> a | shiftleft(shiftright({digits}[i * 64 + p], k) & 1L, p))"
    return F.expr(f"transform(sequence(0, {bits - 1}), k -> transform(sequence(0, (size({digits}) - 1) div 64), i -> {word}))")


def rank(planes: str, bits: int, digit: str, off: str) -> str:
    """SQL: how often digit is among the first off entries. planes may be null if off is 0."""
    match = " & ".join(f"({planes}[{k}][i] ^ (case when shiftright({digit}, {k}) & 1L = 1L then 0L else -1L end))" for k in range(bits))
    tail = f"(case when (i + 1) * 64 <= {off} then -1L else shiftrightunsigned(-1L, cast(64 - ({off} - i * 64) as int)) end)"
    return f"(case when {off} > 0 then aggregate(sequence(0, cast(({off} - 1) div 64 as int)), 0L, (a, i) -> a + bit_count({match} & {tail})) else 0L end)"


def select(planes: str, bits: int, digit: str, nth: str, size: str) -> str:
    """SQL: place (from 0) of the nth (from 1) entry with the digit, null if there are fewer."""
    at = " and ".join(f"(shiftright({planes}[{k}][i div 64], i % 64) & 1L) = (shiftright({digit}, {k}) & 1L)" for k in range(bits))
    return f"get(filter(sequence(0, cast({size} - 1 as int)), i -> {at}), cast({nth} - 1 as int))"
