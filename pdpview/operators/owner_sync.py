"""Owners that upload under a private policy of their own: the release rules on the owner's local queue."""

from __future__ import annotations

import math
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..params import Params
from ..plans.views import ViewSpec
from . import derive, release, steps


def queue(side: DataFrame, strategy: str, p: Params) -> DataFrame:
    """The release rules' trace of the owner's own queue."""
    n = steps.batch_sizes(side)
    grid = n.agg(F.max("step").alias("last")).select(F.explode(F.sequence(F.lit(1), F.coalesce("last", F.lit(1)))).alias("step"))
    q = grid.join(n, "step", "left").select("step", F.coalesce("n", F.lit(0)).alias("n_real"), F.coalesce("n", F.lit(0)).alias("n_true"))
    return release.trace(q, [("owner", strategy, p.but(budget=1, omega=1))])


def uploads(side: DataFrame, strategy: str, p: Params) -> DataFrame:
    """step, arrived, want (rows uploaded, dummies included), real_out, deferred at the owner."""
    return queue(side, strategy, p).select("step", F.col("n_real").alias("arrived"), "want", "real_out", "deferred")


def uploaded(side: DataFrame, traced: DataFrame, p: Params) -> DataFrame:
    """The rows of ``side`` that the owner has sent, each at the step of its upload; first in, first out.

    ``traced`` is ``queue`` of the same side. Rows that a purge discards or that still wait are not there.
    """
    rows = side.withColumns({"born_step": F.col("step"), "l_rid": F.col("rid"), "r_rid": F.lit(0).cast("long")})
    sent = release.place_rows(derive.numbered(rows), traced, p.purge_every, ["rid", "key", "day"])
    return sent.select("rid", "key", "day", F.col("release_step").alias("step"))


def view_sums(spec: ViewSpec, left: DataFrame, right: DataFrame, sent: DataFrame) -> DataFrame:
    """Step summaries of the view over sent rows, with the truth of all rows that the owner has."""
    own = derive.summaries(replace(spec, span=None), sent, right)  # a row may be sent after its partners
    truth = derive.true_pairs(spec, left, right).groupBy(F.col("born_step").alias("step")).agg(F.count("*").alias("real_truth"))
    steps = own.join(truth, "step", "full").fillna(0)
    return steps.drop("n_true").withColumnRenamed("real_truth", "n_true")


def bounded(view: DataFrame, owner: DataFrame, spec: ViewSpec, beta: float = 0.1) -> DataFrame:
    """step, owner_deferred, deferred, answer, truth, l1 and bound: b rows for each row that the owner still holds, and
    the interval rule's bound on rows that wait at the view."""
    p = spec.params
    k = F.greatest(F.floor(F.col("step") / p.interval), F.lit(math.ceil(4 * math.log(1 / beta))))
    bound = p.budget * F.col("owner_deferred") + 2 * p.budget / p.eps * F.sqrt(k * math.log(1 / beta))
    d = view.join(owner.select("step", F.col("deferred").alias("owner_deferred")), "step", "left").fillna(0, ["owner_deferred"])
    return d.select("step", "owner_deferred", "deferred", "answer", "truth", "l1", F.round(bound, 6).alias("bound"))
