"""Entropy, surprisal, filter lengths and the space they need, as Python numbers and as Spark columns."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F


def entropy(p: Sequence[float]) -> float:
    """Bits; zero shares cost nothing."""
    return -sum(x * math.log2(x) for x in p if x > 0)


def surprisal(p: float) -> float:
    return -math.log2(p)


def expected_length(p: Sequence[float], lengths: Sequence[int]) -> float:
    return sum(x * n for x, n in zip(p, lengths, strict=True))


def r_int(minor: int, major: int, cap: int = 64) -> int:
    """Integer filter bits of a decision between weights minor <= major: the least r with 2^(r+1) minor >= major."""
    r = 0
    while r < cap and minor << (r + 1) < major:
        r += 1
    return r


def r_real(p: float) -> float:
    """The best filter length if it could be any real number."""
    return max(0.0, math.log2(math.log(2) * (1 - p) / p))


def space(p: float, r: float) -> float:
    """Bits per key of a weighted membership: filter bits of members, and a correction bit for each that passes."""
    return p * r + p + (1 - p) * 2.0**-r


def binary_entropy(p: float) -> float:
    return entropy((p, 1 - p))


def r_int_column(p: Column) -> Column:
    """r_int for a share p <= 1/2, as the count of powers of two that are still too small."""
    ratio = (F.lit(1.0) - p) / p
    return F.size(F.filter(F.sequence(F.lit(1), F.lit(40)), lambda k: F.pow(F.lit(2.0), k.cast("double")) < ratio))


def space_column(p: Column, r: Column) -> Column:
    return p * r + p + (F.lit(1.0) - p) * F.pow(F.lit(2.0), -r)


def binary_entropy_column(p: Column) -> Column:
    q = F.lit(1.0) - p
    return -(p * F.log2(p) + q * F.log2(q))
