"""Accuracy and cost measures."""

from __future__ import annotations

import math
import time

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

ROW_BYTES, SHARES = 16, 2


def errors(traced: DataFrame, by: list[str]) -> DataFrame:
    """mean_l1, rel_mean (mean of per-step ratios where truth > 0), rel_of_means, for each group of ``by``."""
    l1 = F.abs(F.col("truth") - F.col("answer"))
    return traced.groupBy(*by).agg(
        F.round(F.avg(l1), 6).alias("mean_l1"),
        F.round(F.avg(F.when(F.col("truth") > 0, l1 / F.col("truth"))), 6).alias("rel_mean"),
        F.round(F.avg(l1) / F.avg("truth"), 6).alias("rel_of_means"),
    )


def view_size(traced: DataFrame, by: list[str], row_bytes: int = ROW_BYTES, shares: int = SHARES) -> DataFrame:
    """mean_rows and mean_mb of the view over steps (dummies included, all shares), and the last size."""
    return traced.groupBy(*by).agg(
        F.round(F.avg("view_rows"), 6).alias("mean_rows"),
        F.round(F.avg("view_rows") * row_bytes * shares / 1e6, 6).alias("mean_mb"),
        F.max("view_rows").alias("last_rows"),
    )


def update_frequency(traced: DataFrame, by: list[str]) -> DataFrame:
    """releases and mean gap between them in steps."""
    fired = traced.filter("fires").withColumn("gap", F.col("step") - F.lag("step").over(Window.partitionBy(*by).orderBy("step")))
    return fired.groupBy(*by).agg(F.count("*").alias("releases"), F.round(F.avg("gap"), 6).alias("mean_gap"))


def error_split(traced: DataFrame) -> DataFrame:
    """truth - answer = truncation + retirement + deferred + purge loss, for each run and step."""
    w = Window.partitionBy("run").orderBy("step")
    return traced.select(
        "run", "step", "truth", "answer",
        F.sum(F.col("n_within") - F.col("n_real")).over(w).alias("truncation_loss"),
        F.sum(F.col("n_true") - F.col("n_within")).over(w).alias("retirement_loss"),
        F.col("deferred"),
        F.sum("discarded").over(w).alias("purge_loss"),
    )


def buffer_rows(traced: DataFrame) -> DataFrame:
    """Padded rows that the buffer holds after each step; a purge empties it."""
    w = Window.partitionBy("run", "epoch").orderBy("step")
    held = F.greatest(F.lit(0), F.sum(F.col("n_padded") - F.col("want")).over(w))
    return traced.select("run", "step", F.when(F.col("step") % F.col("purge_every") == 0, 0).otherwise(held).cast("long").alias("buffer_rows"), "deferred")


def oblivious_cost(n: Column) -> Column:
    """Compare-exchanges of a bitonic network over n rows padded to a power of two."""
    lg = F.ceil(F.log2(F.greatest(n, F.lit(1)).cast("double")))
    return (F.pow(F.lit(2.0), lg) / 4 * lg * (lg + 1)).cast("long")


def oblivious_cost_value(n: int) -> int:
    lg = math.ceil(math.log2(max(n, 1)))
    return (1 << lg) * lg * (lg + 1) // 4


def work(traced: DataFrame) -> DataFrame:
    """Modelled oblivious work by run: derive sorts inputs, release sorts the buffer, a query scans the view."""
    b = buffer_rows(traced).select("run", "step", "buffer_rows")
    held = F.lag("buffer_rows", 1, 0).over(Window.partitionBy("run").orderBy("step")) + F.col("n_padded")
    d = traced.join(b, ["run", "step"]).withColumn("sorted", held)
    return d.groupBy("run").agg(
        F.sum(oblivious_cost(F.col("n_padded"))).alias("derive_work"),
        F.sum(F.when(F.col("fires"), oblivious_cost(F.col("sorted"))).otherwise(0)).alias("release_work"),
        F.sum("view_rows").alias("query_work"),
    )


def improvement(table: DataFrame, base: str, value: str, strategy: str = "strategy") -> DataFrame:
    """strategy, gain: how many times smaller ``value`` is than the base strategy's."""
    b = table.filter(F.col(strategy) == base).agg(F.first(value).alias("base"))
    return table.crossJoin(F.broadcast(b)).select(strategy, F.round(F.col("base") / F.nullif(F.col(value), F.lit(0)), 4).alias("gain"))


def timed(df: DataFrame) -> float:
    """Seconds to run ``df`` to its end."""
    t = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t
