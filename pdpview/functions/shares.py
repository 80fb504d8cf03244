"""XOR sharing over 32-bit words, on columns of type BIGINT in [0, 2**32)."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

RING = (1 << 32) - 1


def split(value: Column, word: Column) -> list[Column]:
    """A random word and the value under its mask."""
    return [word, word.bitwiseXOR(value)]


def recover(*shares: Column) -> Column:
    return reduce(lambda a, b: a.bitwiseXOR(b), shares)


def reshare(value: Column, *contributed: Column) -> list[Column]:
    """Both servers contribute a word; neither alone knows the mask, their xor."""
    return split(value, recover(*contributed))


def split_n(value: Column, words: list[Column]) -> list[Column]:
    """One share for each server: all but one are random words, the last closes the xor."""
    return [*words, recover(value, *words)]


def recover_array(shares: Column) -> Column:
    return F.aggregate(shares, F.lit(0).cast("long"), lambda a, x: a.bitwiseXOR(x))
