"""The release rules a second time, as a table function that walks one run's steps: a check on the set-based form."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import release
from ..params import Params


def walk(strategy: str, arrivals: list[int], noises: list[dict], p: dict) -> list[tuple]:
    """(step, c, fires, want, real_out, deferred, discarded) by plain iteration; ``noises`` has chk, rel, thr by step."""
    c, depth, bound, out = 0, 0, p["theta"] + p["thr0"], []
    for t, (a, z) in enumerate(zip(arrivals, noises, strict=True), 1):
        c, depth = c + a, depth + a
        seen = c
        fires = t % p["every_steps"] == 0 if strategy == "interval" else c + z["chk"] >= bound
        want = real = gone = 0
        if fires:
            want = max(0, int((c + z["rel"] + 0.5) // 1))
            real = min(want, depth)
            depth -= real
            c = 0
            bound = p["theta"] + z["thr"]
        if t % p["purge_every"] == 0:
            gone = max(0, depth - p["purge_size"])
            depth = 0
            if p.get("purge_resets_counter"):
                c = 0
        out.append((t, seen, bool(fires), want, real, depth, gone))
    return out


def trace_with_udtf(sums: DataFrame, runs: list[tuple[str, str, Params]]) -> DataFrame:
    """run, step, c, fires, want, real_out, deferred, discarded, one call of the table function for each run."""
    spark = sums.sparkSession

    @F.udtf(returnType="step int, c long, fires boolean, want long, real_out long, deferred long, discarded long")
    class ReleaseTrace:
        def eval(self, strategy, arrivals, chk, rel, thr, every_steps, theta, thr0, purge_every, purge_size, resets):
            noises = [{"chk": a, "rel": b, "thr": c} for a, b, c in zip(chk, rel, thr, strict=True)]
            yield from walk(strategy, arrivals, noises, {"every_steps": every_steps, "theta": theta, "thr0": thr0, "purge_every": purge_every, "purge_size": purge_size, "purge_resets_counter": resets})

    spark.udtf.register("pdpview_release_trace", ReleaseTrace)
    steps = release.threshold_noise(release.with_runs(sums, runs))
    scale = F.when(F.col("strategy") == "interval", 0.5).otherwise(1.0)  # interval noise has half the release scale of the threshold rule
    steps = steps.withColumn("rel", F.when(F.col("mech") & (F.col("strategy") == "interval"), F.col("rel") / 4).otherwise(F.col("rel") * scale)).withColumn("thr0", F.col("thr0") - F.col("theta"))
    arrays = steps.groupBy("run", "strategy", "every_steps", "theta", "thr0", "purge_every", "purge_size", "resets").agg(F.array_sort(F.collect_list(F.struct("step", "n_real", "chk", "rel", "thr"))).alias("a"))
    arrays = arrays.select("*", *(F.col(f"a.{c}").alias(f"a_{c}") for c in ("n_real", "chk", "rel", "thr")))
    arrays.createOrReplaceTempView("pdpview_runs")
    return spark.sql(
        "SELECT r.run, t.* FROM pdpview_runs r, LATERAL pdpview_release_trace(strategy, a_n_real, a_chk, a_rel, a_thr, every_steps, theta, thr0, purge_every, purge_size, resets) t"
    )


