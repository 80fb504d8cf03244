"""Stream operators around the views: deduplication, windowed counts, interval joins, stateful release."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.noise import HALF
from ..params import Params


def event_time(events: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """Zone-less times are refused by watermarks: cast first."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness)


def deduplicated(events: DataFrame) -> DataFrame:
    return event_time(events).dropDuplicatesWithinWatermark(["event_id"])


def window_counts(events: DataFrame, width: str = "12 hours") -> DataFrame:
    return event_time(events).groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n"))


def interval_join(events_a: DataFrame, events_b: DataFrame, hours: int = 24) -> DataFrame:
    """Errors with the same user's purchases within ``hours``, both sides streaming."""
    a = event_time(events_a).filter("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col("user_id").alias("u"), F.col("ts").alias("a"))
    b = event_time(events_b).filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("v"), F.col("ts").alias("b"))
    return a.join(b, (F.col("u") == F.col("v")) & (F.col("b") >= F.col("a")) & (F.col("b") <= F.col("a") + F.expr(f"INTERVAL {hours} HOURS"))).select("error_id", "purchase_id")


RELEASES = "view string, step int, c long, fires boolean, want long"


def threshold_releases(steps: DataFrame, p: Params) -> DataFrame:
    """The threshold rule as a stateful operator: rows (view, step, n_real, chk, rel, thr words) in, commands out.

    State by view: counter, bound, last step. Steps of a view must come in order over the batches; inside one they
    are sorted here, and steps already seen (a replay) are passed over.
    """
    import math

    scale = p.budget / p.eps

    def lap(word: int, k: float) -> float:
        return k * scale * math.log(((int(word) & (HALF - 1)) + 0.5) / HALF) * (1 if int(word) >= HALF else -1)

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        c, bound, last = state.get if state.exists else (0, None, 0)
        rows = pd.concat(list(frames)).sort_values("step")
        out = []
        for r in rows.itertuples():
            if r.step <= last:
                continue
            if bound is None:
                bound = p.theta + lap(r.thr0, 4)
            c += int(r.n_real)
            fires = c + lap(r.chk, 8) >= bound
            want = max(0, math.floor(c + lap(r.rel, 2) + 0.5)) if fires else 0
            out.append((key[0], int(r.step), c, bool(fires), want))
            if fires:
                c, bound = 0, p.theta + lap(r.thr, 4)
            last = int(r.step)
        state.update((c, bound, last))
        yield pd.DataFrame(out, columns=["view", "step", "c", "fires", "want"])

    return steps.groupBy("view").applyInPandasWithState(step, RELEASES, "c long, bound double, last int", "append", "NoTimeout")
