"""Contribution budgets: a use costs omega whatever it yields, so a budget is a horizon of steps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..params import Params


def active(df: DataFrame, t: int, p: Params) -> DataFrame:
    """Rows that may be used at step ``t``: a range of steps, so partitions by step are pruned."""
    return df.filter((F.col("step") <= t) & (F.col("step") > t - p.horizon))


def ledger(df: DataFrame, t: int, p: Params) -> DataFrame:
    """rid, key, step, used, left at step ``t`` by charging each use."""
    uses = F.greatest(F.lit(0), F.least(F.lit(t) - F.col("step") + 1, F.lit(p.horizon)))
    used = (uses * p.omega).cast("long")
    return df.select("rid", "key", "step", used.alias("used"), (F.lit(p.budget) - used).alias("budget_left"))


def retired(df: DataFrame, t: int, p: Params) -> DataFrame:
    return df.filter(F.col("step") <= t - p.horizon)
