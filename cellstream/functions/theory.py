"""Closed forms of the uniform analysis: bits, factors, gains, work."""

from __future__ import annotations

import math
from math import ceil, inf

SEPARATION = 2.402


def log2(n: float) -> float:
    """As SQL has it: minus infinity for an empty set."""
    return math.log2(n) if n else -inf


def separation_bits(n: int) -> float:
    return SEPARATION * n


def localisation_bits(n: int, q: int) -> float:
    return n * (q - log2(n))


def total_bits(n: int, q: int) -> float:
    return separation_bits(n) + localisation_bits(n, q)


def gain(n: int, arithmetic: bool = True) -> float:
    """Bits saved per point against raw coordinates."""
    return log2(n) - (SEPARATION if arithmetic else 3)


def order_bits(n: int) -> float:
    return n * log2(n)


def factor(n: int, q: int) -> float:
    return q / (q - log2(n) + SEPARATION)


def source_bytes(n: int, q: int) -> int:
    return ceil(n * q / 8)


def wave_bound(n: int, level: int) -> float:
    """Most bits that one wave can cost, for any multiset of n points."""
    return min(float(n), 2.0**level * log2(1 + n / 2**level))


def ratio(n: int, q: int) -> float:
    return q / log2(n)


def coder_time(n: int, q: int) -> int:
    return n * q


def decoder_time(n: int, q: int) -> float:
    return n * (q - log2(n) + 1)


def space(n: int, q: int) -> int:
    return n * (q + 4)
