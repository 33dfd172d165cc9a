"""Sets of columns as bits: Python integers in kernels, 63-bit words in DataFrames."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = 63
MASK = (1 << WORD) - 1


def words(n: int) -> int:
    return max(1, -(-n // WORD))


def split(bits: int, n_words: int) -> list[int]:
    return [(bits >> (WORD * i)) & MASK for i in range(n_words)]


def join(parts) -> int:
    return sum(int(p) << (WORD * i) for i, p in enumerate(parts))


def members(bits: int) -> list[int]:
    out = []
    while bits:
        low = bits & -bits
        out.append(low.bit_length() - 1)
        bits ^= low
    return out


def names(bits: int, order: list[str]) -> list[str]:
    return sorted(order[p] for p in members(bits))


def from_names(chosen: list[str], order: list[str]) -> int:
    return sum(1 << order.index(c) for c in chosen)


def contains(whole: Column, part: Column) -> Column:
    return part.bitwiseAND(F.bitwise_not(whole)) == 0


def bit(word: int, position: Column, n: int) -> Column:
    """The bit of `position` (of n) in word number `word`, 0 if it lies in another."""
    values = [1 << p % WORD if p // WORD == word else 0 for p in range(n)]
    return F.element_at(F.array(*(F.lit(v).cast("long") for v in values)), position + 1)


def size(parts: list[Column]) -> Column:
    return reduce(Column.__add__, (F.bit_count(p) for p in parts))


def any_set(parts: list[Column]) -> Column:
    return reduce(Column.__or__, (p != 0 for p in parts))
