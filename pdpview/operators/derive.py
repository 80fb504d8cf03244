"""The derive stage: new view rows of every upload step, truncated, with the secret counter's increments."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..params import Params
from ..plans.views import ViewSpec
from . import truncate


def true_pairs(spec: ViewSpec, left: DataFrame, right: DataFrame) -> DataFrame:
    """Logical view rows, each at the step that completes it: born_step, key, l_rid, r_rid, l_step, r_step, r_day."""
    on = ["key"]
    if spec.span is not None:
        # a key's history in stretches of span + 1 steps: a left row meets right rows of its own stretch and the next
        left, right = (d.withColumn("__near", F.floor(F.col("step") / (spec.span + 1))) for d in (left, right))
        left, on = left.withColumn("__near", F.explode(F.array(F.col("__near"), F.col("__near") + 1))), ["key", "__near"]
    met = [F.col(f"l.{c}") == F.col(f"r.{c}") for c in on]
    pairs = left.alias("l").join(right.alias("r"), met).filter(spec.lag_ok())
    return pairs.select(
        F.greatest("l.step", "r.step").alias("born_step"), F.col("l.key").alias("key"), F.col("l.rid").alias("l_rid"), F.col("r.rid").alias("r_rid"),
        F.col("l.step").alias("l_step"), F.col("r.step").alias("r_step"), F.col("r.day").alias("r_day"),
    )


def late(spec: ViewSpec) -> Column:
    """Steps between a pair's oldest private row and the step that completes the pair."""
    return F.col("born_step") - (F.col("l_step") if spec.right_public else F.least("l_step", "r_step"))


def within_horizon(spec: ViewSpec, pairs: DataFrame) -> DataFrame:
    """Pairs whose private rows still have budget when the pair is completed."""
    return pairs.filter(late(spec) < spec.params.horizon)


def derive(spec: ViewSpec, left: DataFrame, right: DataFrame) -> DataFrame:
    """View rows of all invocations in one job: born_step, key, l_rid, r_rid."""
    p = spec.params
    if spec.right_public:
        pairs = within_horizon(spec, true_pairs(spec, left, right))
        kept = truncate.cap_private(pairs, ["born_step", "key", "l_rid"], ["r_day", "r_rid"], p.omega)
    elif spec.is_pure_equi:
        kept = derive_blocks(left, right, p)
    else:
        kept = truncate.scan(within_horizon(spec, true_pairs(spec, left, right)), ["born_step", "key"], p.omega)
    return kept.select("born_step", "key", "l_rid", "r_rid")


def derive_blocks(left: DataFrame, right: DataFrame, p: Params) -> DataFrame:
    """Two private sides, right rows never before left ones: invocation t pairs new right rows with active left rows.

    Left rows are repeated for the steps of their horizon, but only where their key arrives on the other side.
    """
    new = right.select(F.col("key"), F.col("step").alias("born_step"), F.col("rid").alias("r_rid"))
    arrivals = new.select("key", "born_step").distinct()
    # a join on the key with the step range as residual replaces the explode: no copy is made that meets nothing
    old = left.select("key", "step", F.col("rid").alias("l_rid")).join(arrivals, "key").filter((F.col("born_step") >= F.col("step")) & (F.col("born_step") < F.col("step") + p.horizon))
    return truncate.merge_join(old.withColumnRenamed("step", "l_step"), new, ["born_step", "key"], ["l_step", "l_rid"], ["r_rid"], p.omega)


def increment(spec: ViewSpec, left: DataFrame, right: DataFrame, t: int) -> DataFrame:
    """One invocation: reads only the new step and the horizon before it (all public rows so far, if they may come first)."""
    h = spec.params.horizon
    recent = lambda d: d.filter((F.col("step") <= t) & (F.col("step") > t - h))
    other = right.filter(F.col("step") <= t) if spec.right_public and spec.span is None else recent(right)
    return derive(spec, recent(left), other).filter(F.col("born_step") == t)


def summaries(spec: ViewSpec, left: DataFrame, right: DataFrame, strict: bool = True) -> DataFrame:
    """step, n_true, n_within, n_real, n_padded, n_left, n_right, up_left, up_right for every step; some thousand rows.

    ``n_left`` and ``n_right`` are the owners' secret batch sizes, ``up_left`` and ``up_right`` what they upload:
    batches padded to their public size (a public side uploads as it is). Padded sizes rest on uploads alone. A batch
    above its declared size is an error, not a leak; only without ``strict`` is it shown at that size all the same, and
    its rows beyond it are derived and counted as the others. Such a summary says what an observer of declared sizes
    is shown, not that the batch fits them.
    """
    p = spec.params
    count = lambda d, c, n: d.groupBy(F.col(c).alias("step")).agg(F.count("*").alias(n))
    truth = true_pairs(spec, left, right).withColumn("__in", late(spec) < p.horizon)
    if spec.right_public:
        # one pass: partners inside the horizon are ranked, and those beyond the bound only counted
        rank = F.row_number().over(Window.partitionBy("born_step", "key", "l_rid", "__in").orderBy("r_day", "r_rid"))
        truth = truth.withColumn("__kept", F.col("__in") & (rank <= p.omega))
        parts = [truth.groupBy(F.col("born_step").alias("step")).agg(F.count("*").alias("n_true"), F.count_if("__in").alias("n_within"), F.count_if("__kept").alias("n_real"))]
    else:
        parts = [truth.groupBy(F.col("born_step").alias("step")).agg(F.count("*").alias("n_true"), F.count_if("__in").alias("n_within")), count(derive(spec, left, right), "born_step", "n_real")]
    parts += [count(left, "step", "n_left"), count(right, "step", "n_right")]
    sums = parts[0]
    for part in parts[1:]:
        sums = sums.join(part, "step", "full")
    last = sums.agg(F.max("step").alias("last"))
    grid = last.select(F.explode(F.sequence(F.lit(1), F.coalesce("last", F.lit(1)))).alias("step"))
    sums = grid.join(sums, "step", "left").fillna(0)
    whole, active = Window.partitionBy(), Window.orderBy("step").rowsBetween(-(p.horizon - 1), 0)
    for k, side in enumerate(("left", "right")):
        n = F.col(f"n_{side}")
        declared = F.max(n).over(whole) if p.batch_cap is None else F.lit(p.batch_cap[k])
        padded = declared
        if strict:
            padded = F.when(n <= declared, declared).otherwise(F.raise_error(F.concat(F.lit(f"a {side} batch is larger than its declared size: "), n.cast("string"))).cast("long"))
        sums = sums.withColumn(f"up_{side}", (n if side == "right" and spec.right_public else padded).cast("long"))
    private = F.col("up_left") + (F.lit(0) if spec.right_public else F.col("up_right"))
    padded = p.budget * private if p.pad_rule == "budget" else p.omega * F.sum(private).over(active)
    return sums.withColumn("n_padded", padded.cast("long")).select("step", "n_true", "n_within", "n_real", "n_padded", "n_left", "n_right", "up_left", "up_right")


def counter(sums: DataFrame) -> DataFrame:
    """step, n_real, c: the counter if it were never reset."""
    return sums.select("step", "n_real", F.sum("n_real").over(Window.orderBy("step")).alias("c"))


#: Parts of a step that are numbered apart.
PARTS = 64


def part_of_step() -> Column:
    return F.pmod(F.col("key") + F.col("l_rid"), F.lit(PARTS))


def numbered(pairs: DataFrame) -> DataFrame:
    """Pairs with ``ord``, their place among the pairs of their step: numbered inside parts of a step, whose offsets
    come from one count for each part, so no task holds a step."""
    d = pairs.withColumn("__part", part_of_step())
    inner = F.row_number().over(Window.partitionBy("born_step", "__part").orderBy("key", "l_rid", "r_rid"))
    sizes = d.groupBy("born_step", "__part").agg(F.count("*").alias("__n"))  # PARTS rows a step at most
    before = sizes.select("born_step", "__part", (F.sum("__n").over(Window.partitionBy("born_step").orderBy("__part")) - F.col("__n")).alias("__before"))
    return d.withColumn("__i", inner).join(F.broadcast(before), ["born_step", "__part"]).withColumn("ord", (F.col("__before") + F.col("__i")).cast("long")).drop("__part", "__i", "__before")
