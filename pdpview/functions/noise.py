"""Joint noise: the xor of the servers' words gives a sign and a seed, and these a Laplace variate."""

from __future__ import annotations

import math
import secrets
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import stored

HALF = 1 << 31


def hash_word(*parts: Column | str) -> Column:
    """A reproducible 32-bit word: for tests and oracles only, never for a deployed view."""
    text = F.concat_ws("|", *(p.cast("string") if isinstance(p, Column) else F.lit(p) for p in parts))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def joint_word(seed: Column | str, purpose: str, step: Column, servers: int = 2) -> Column:
    return reduce(lambda a, b: a.bitwiseXOR(b), [hash_word(seed, f"s{k}", purpose, step) for k in range(servers)])


def laplace(word: Column, scale: Column | float) -> Column:
    """Top bit: sign; low 31 bits: seed in (0, 1), so sign and size are independent."""
    r = (word.bitwiseAND(HALF - 1) + F.lit(0.5)) / F.lit(float(HALF))
    scale = scale if isinstance(scale, Column) else F.lit(float(scale))
    return scale * F.log(r) * F.when(word >= HALF, 1.0).otherwise(-1.0)


def joint_laplace(z0: Column, z1: Column, scale: Column | float) -> Column:
    return laplace(z0.bitwiseXOR(z1), scale)


def laplace_value(word: int, scale: float) -> float:
    """The same on plain numbers."""
    return scale * math.log(((word & (HALF - 1)) + 0.5) / HALF) * (1 if word >= HALF else -1)


def geometric(word: Column, scale: Column | float) -> Column:
    """Two-sided geometric noise, P(k) in proportion to exp(-|k| / scale): integers, without the low-order bits of a
    real variate. Low 31 bits: the size, by inversion of P(|k| >= m) = 2 q^m / (1 + q); top bit: the sign."""
    scale = scale if isinstance(scale, Column) else F.lit(float(scale))
    r = (word.bitwiseAND(HALF - 1) + F.lit(0.5)) / F.lit(float(HALF))
    q = F.exp(-1 / scale)
    size = F.greatest(F.lit(0), F.floor(F.log(r * (1 + q) / (2 * q)) / F.log(q)) + 1)
    return (size * F.when(word >= HALF, 1).otherwise(-1)).cast("long")


def system_words(spark: SparkSession, steps: int, purposes: list[str], servers: int = 2) -> DataFrame:
    """Fresh words for every (step, purpose, server); store them before use, so that a retry does not draw twice."""
    rows = [(t, p, k, secrets.randbits(32)) for t in range(steps + 1) for p in purposes for k in range(servers)]
    return spark.createDataFrame(rows, "step int, purpose string, server int, word long")


def drawn_words(spark: SparkSession, runs: list[str], last: int, purposes: tuple[str, ...], servers: int = 2) -> DataFrame:
    """run, step 0..last and the servers' joint word for each purpose, drawn from the system once and stored."""
    rows = [(r, t, *(reduce(lambda a, b: a ^ b, (secrets.randbits(32) for _ in range(servers))) for _ in purposes)) for r in runs for t in range(last + 1)]
    return stored(spark.createDataFrame(rows, "run string, step int, " + ", ".join(f"word_{k} long" for k in purposes)), "words")
