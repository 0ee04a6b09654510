"""Bit vectors as flat 64-bit words ``w0 .. w{m/64-1}``, so that comparison stays inside generated code."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


def names(m: int, prefix: str = "w") -> list[str]:
    return [f"{prefix}{i}" for i in range(m // 64)]


def word_of(positions: Column, word: int) -> Column:
    """The bits of one word among an array of positions."""
    inside = F.filter(positions, lambda p: F.floor(p / 64) == word)
    return F.aggregate(inside, F.lit(0).cast("long"), lambda total, p: total.bitwiseOR(_shift(p)))


def _shift(position: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod(position, F.lit(64)).cast("int"))


def pack(positions: Column, m: int) -> list[Column]:
    """Words of an array of positions."""
    return [word_of(positions, i).alias(n) for i, n in enumerate(names(m))]


def popcount(words: Sequence[Column]) -> Column:
    return reduce(lambda a, b: a + b, (F.bit_count(w) for w in words))


def fill_rate(ones: Column, m: int) -> Column:
    return ones / float(m)


def unpack(words: Sequence[Column]) -> Column:
    """Sorted array of the set positions."""
    bit = lambda i, w: F.transform(
        F.filter(F.sequence(F.lit(0), F.lit(63)), lambda k: F.call_function("getbit", w, k) == 1), lambda k: k + 64 * i
    )
    return F.flatten(F.array(*(bit(i, w) for i, w in enumerate(words))))
