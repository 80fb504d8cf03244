"""Privacy accounting and utility bounds."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def through_stable(q: float, eps: float) -> float:
    """Loss on the input of a q-stable transformation whose output an eps-private mechanism reads."""
    return q * eps


def composed(uses: DataFrame, losses: DataFrame) -> DataFrame:
    """One row ``eps``: the most that any row's uses (rid, invocation, q) add up to; ``losses``: invocation, eps."""
    total = uses.join(losses, "invocation").groupBy("rid").agg(F.sum(F.col("q") * F.col("eps")).alias("spent"))
    return total.agg(F.max("spent").alias("eps"))


def deferred_bound_interval(eps: float, budget: int, releases: int, beta: float) -> float:
    """Deferred rows exceed this after ``releases`` releases with probability at most ``beta``."""
    if releases < 4 * math.log(1 / beta):
        raise ValueError("the bound needs at least 4 log(1/beta) releases")
    return 2 * budget / eps * math.sqrt(releases * math.log(1 / beta))


def view_bound_interval(eps: float, budget: int, releases: int, interval: int, every: int, size: int, beta: float = 0.1) -> float:
    """Bound on dummy rows in the view; the constant of its first term is that of the deferred bound."""
    return deferred_bound_interval(eps, budget, releases, beta) + size * releases * interval / every


def bounds_threshold(eps: float, budget: int, step: int, every: int, size: int) -> tuple[float, float]:
    """(deferred rows, dummy rows in the view) at ``step``, up to constants."""
    d = 16 * budget * math.log(max(step, 2)) / eps
    return d, d + size * (step // every)


def purge_size(eps: float, budget: int, releases: int, beta: float) -> int:
    """A purge that loses real rows with probability at most ``beta``."""
    return math.ceil(deferred_bound_interval(eps, budget, max(releases, math.ceil(4 * math.log(1 / beta))), beta))


def user_level(eps: float, rows_per_user: int) -> float:
    """Event-level parameter that gives ``eps`` for a user with so many rows."""
    return eps / rows_per_user


def rows_per_user(df: DataFrame, user: str) -> DataFrame:
    """One row ``ell``: the most rows that one user owns."""
    return df.groupBy(user).agg(F.count("*").alias("n")).agg(F.max("n").alias("ell"))


def correlated_range(eps: float, rows: int) -> tuple[float, float]:
    """Event-level loss under correlated rows lies between these."""
    return eps, rows * eps


def compose_owner(eps_owner: float, eps_view: float) -> float:
    """Total loss when owners upload by a private policy of their own."""
    return eps_owner + eps_view


def error_owner(budget: int, owner_error: float, view_error: float) -> float:
    """Error of a view over privately uploaded data: each row missing at the owner costs up to ``budget`` view rows."""
    return budget * owner_error + view_error
