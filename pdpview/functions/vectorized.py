"""Vectorized Python twins of built-in expressions, for cross-checks and for users who need them in Python."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .noise import HALF


def laplace_udf(word: Column, scale: float) -> Column:
    """Joint noise from words as a pandas function."""

    @F.pandas_udf("double")
    def draw(z: pd.Series) -> pd.Series:
        r = ((z.to_numpy() & (HALF - 1)) + 0.5) / HALF
        return pd.Series(scale * np.log(r) * np.where(z.to_numpy() >= HALF, 1.0, -1.0))

    return draw(word)


def max_contribution_udaf(pairs: DataFrame, step: str, rid: str) -> DataFrame:
    """step, most: the largest number of pairs of one row in each step, as a grouped-aggregate pandas function."""

    @F.pandas_udf("long")
    def most(r: pd.Series) -> int:
        return int(r.value_counts().max()) if len(r) else 0

    return pairs.groupBy(step).agg(most(F.col(rid)).alias("most"))
