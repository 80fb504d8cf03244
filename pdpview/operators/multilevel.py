"""Views over views: each level derives from what the level below released, with a part of the privacy budget."""

from __future__ import annotations

import math
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import privacy
from ..params import Params
from ..plans.views import ViewSpec
from . import derive, metrics, release, truncate


def chain(sums: DataFrame, levels: list[tuple[str, Params]]) -> DataFrame:
    """The last level's trace; ``levels`` are (strategy, parameters) from the bottom up."""
    now, out = sums, None
    for k, (strategy, p) in enumerate(levels):
        out = release.trace(now, [(f"level{k + 1}", strategy, p)])
        now = out.select("step", (F.col("real_out") + F.col("purge_real")).alias("n_real"), "n_true")
    return out


def released_rows(side: DataFrame, keep, strategy: str, p: Params) -> tuple[DataFrame, DataFrame]:
    """A first level with the filter as its operator: (its trace, its released rows at their release step).

    The filter is oblivious: every row stays in the padded output and the failing ones become dummies.
    """
    marked = truncate.oblivious_filter(side, keep)
    per_step = marked.groupBy("step").agg(F.count("*").alias("n_padded"), F.count_if("is_view").alias("n_real"))
    grid = per_step.agg(F.max("step").alias("last")).select(F.explode(F.sequence(F.lit(1), F.coalesce("last", F.lit(1)))).alias("step"))
    sums = grid.join(per_step, "step", "left").fillna(0).withColumn("n_true", F.col("n_real"))
    traced = release.trace(sums, [("filter", strategy, p)])
    rows = marked.filter("is_view").withColumns({"born_step": F.col("step"), "l_rid": F.col("rid"), "r_rid": F.lit(0).cast("long")})
    out = release.place_rows(derive.numbered(rows), traced, p.purge_every, ["rid", "key", "day"])
    return traced, out.select("rid", "key", "day", F.col("release_step").alias("step"))


def filter_then_join(spec: ViewSpec, left: DataFrame, right: DataFrame, keep, first: tuple[str, Params], second: tuple[str, Params]) -> DataFrame:
    """Two operators, each with a derive and a release stage of its own: level 1 filters the left side and releases the
    rows that pass, level 2 joins what was released with the right side and releases pairs. The second level's trace;
    its truth is that of the whole query over all data. Losses of the levels add up."""
    _, rows = released_rows(left, keep, *first)
    own = derive.summaries(replace(spec, span=None), rows, right)  # released rows may come after their partners
    truth = derive.true_pairs(spec, left.filter(keep), right).groupBy(F.col("born_step").alias("step")).agg(F.count("*").alias("whole"))
    sums = own.join(truth, "step", "full").fillna(0).drop("n_true").withColumnRenamed("whole", "n_true")
    return release.trace(sums, [("level2", *second)])


def work_of(rows: int, eps: float, budget: int, releases: int, beta: float) -> int:
    """Modelled oblivious work of one level: each release sorts the buffer, which holds the level's rows of a release
    and as many dummies as noise of that budget leaves."""
    extra = privacy.deferred_bound_interval(eps, budget, max(releases, math.ceil(4 * math.log(1 / beta))), beta)
    return releases * metrics.oblivious_cost_value(math.ceil(rows / max(releases, 1) + extra))


def allocate(eps: float, levels: list[tuple[int, int]], releases: int, most_error: float, beta: float = 0.1, grid: int = 40) -> tuple[list[float], int, float] | None:
    """The split of ``eps`` over levels with the least work whose errors stay within ``most_error``: (split, work,
    error), by search over ``grid`` shares; None if no split keeps the error. ``levels`` are (rows, budget); a level's
    error is the bound on its deferred rows."""
    k = max(releases, math.ceil(4 * math.log(1 / beta)))

    def splits(left: int, n: int):
        if n == 1:
            yield [left]
            return
        for first in range(1, left - n + 2):
            for rest in splits(left - first, n - 1):
                yield [first, *rest]

    best = None
    for shares in splits(grid, len(levels)):
        parts = [eps * x / grid for x in shares]
        error = sum(privacy.deferred_bound_interval(e, b, k, beta) for e, (_, b) in zip(parts, levels, strict=True))
        work = sum(work_of(n, e, b, releases, beta) for e, (n, b) in zip(parts, levels, strict=True))
        if error <= most_error and (best is None or (work, error) < best[1:]):
            best = (parts, work, error)
    return best
