"""The release stage on step summaries: when to read the buffer, how much, and which rows that is.

Everything here works on one row for each run and step (some thousand rows a view). Runs are parameter settings
or seeds, computed side by side.
"""

from __future__ import annotations

from collections.abc import Iterable

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import noise
from ..params import Params

RUN_SCHEMA = "run string, strategy string, eps double, budget int, every_steps int, theta double, purge_every int, purge_size int, seed string, mech boolean, resets boolean"
PURPOSES = ("chk", "rel", "thr")


def runs_frame(spark: SparkSession, runs: Iterable[tuple[str, str, Params]]) -> DataFrame:
    rows = [(n, s, p.eps, p.budget, p.interval, float(p.theta), p.purge_every, p.purge_size, p.seed, p.scale_release == "mechanism", p.purge_resets_counter) for n, s, p in runs]
    return spark.createDataFrame(rows, RUN_SCHEMA)


def with_runs(sums: DataFrame, runs: Iterable[tuple[str, str, Params]]) -> DataFrame:
    """Every step for every run, with the words of its noise: word_chk, word_rel, word_thr, and word_thr0 of step 0.

    Words of runs with ``system_noise`` are drawn from the system here and stored before anything reads them, so a
    retried task or a second reading of the frame sees the same noise.
    """
    runs = list(runs)
    steps = sums.crossJoin(F.broadcast(runs_frame(sums.sparkSession, runs)))
    hashed = {f"word_{k}": noise.joint_word(F.col("seed"), k, F.col("step")) for k in PURPOSES}
    hashed["word_thr0"] = noise.joint_word(F.col("seed"), "thr", F.lit(0))
    drawn = [n for n, _, p in runs if p.system_noise]
    if not drawn:
        return steps.withColumns(hashed)
    last = sums.agg(F.max("step")).first()[0] or 0
    words = noise.drawn_words(sums.sparkSession, drawn, last, PURPOSES)
    start = words.filter("step = 0").select("run", F.col("word_thr").alias("own_thr0"))
    own = words.select("run", "step", *(F.col(f"word_{k}").alias(f"own_{k}") for k in PURPOSES))
    steps = steps.join(F.broadcast(own), ["run", "step"], "left").join(F.broadcast(start), "run", "left")
    mine = [f"own_{k}" for k in (*PURPOSES, "thr0")]
    return steps.withColumns({f"word_{c[4:]}": F.coalesce(c, hashed[f"word_{c[4:]}"]) for c in mine}).drop(*mine)


def per_run(order: str = "step") -> Window:
    return Window.partitionBy("run").orderBy(order)


def rounded(sz: Column) -> Column:
    return F.greatest(F.lit(0), F.floor(sz + 0.5)).cast("long")


def since_purge() -> Column:
    """The purge epoch where a purge resets the counter, else 0."""
    return F.when(F.col("resets"), F.floor((F.col("step") - 1) / F.col("purge_every"))).otherwise(F.lit(0))


def interval_sizes(steps: DataFrame) -> DataFrame:
    """Adds c (counter at the check), fires, sz, want (rows to read) for the interval rule."""
    turn = F.floor((F.col("step") - 1) / F.col("every_steps"))
    steps = steps.withColumn("c", F.sum("n_real").over(Window.partitionBy("run", turn, since_purge()).orderBy("step")))
    fires = F.col("step") % F.col("every_steps") == 0
    z = noise.laplace(F.col("word_rel"), F.col("budget") / F.col("eps"))
    return steps.withColumn("fires", fires).withColumn("sz", F.when(fires, F.col("c") + z)).withColumn("want", F.when(fires, rounded(F.col("sz"))).otherwise(F.lit(0).cast("long")))


def threshold_noise(steps: DataFrame) -> DataFrame:
    """Adds chk, rel and thr, the noise that each step would use; the rule only selects among them."""
    scale = F.col("budget") / F.col("eps")
    rel = noise.laplace(F.col("word_rel"), scale * F.when(F.col("mech"), 4.0).otherwise(2.0))
    steps = steps.withColumns({"chk": noise.laplace(F.col("word_chk"), scale * 8.0), "thr": noise.laplace(F.col("word_thr"), scale * 4.0), "rel": rel})
    return steps.withColumn("thr0", F.col("theta") + noise.laplace(F.col("word_thr0"), scale * 4.0))


def threshold_sizes(steps: DataFrame) -> DataFrame:
    """As ``interval_sizes`` for the noisy-threshold rule: each run's steps are folded in order, as one expression over
    the run's array of steps (some thousand; the fold's output grows by one struct a step)."""
    steps = threshold_noise(steps)
    flush = F.col("resets") & (F.col("step") % F.col("purge_every") == 0)
    s = F.struct("step", "n_real", "chk", "thr", "rel", "theta", flush.alias("flush"))
    arrays = steps.groupBy("run", "thr0").agg(F.array_sort(F.collect_list(s)).alias("steps"))
    kind = "array<struct<step:int,c:bigint,bound:double,fires:boolean,sz:double>>"
    start = F.struct(F.lit(0).cast("long").alias("c"), F.col("thr0").alias("bound"), F.array().cast(kind).alias("out"))

    def turn(acc: Column, x: Column) -> Column:
        c = acc["c"] + x["n_real"]
        fires = c + x["chk"] >= acc["bound"]
        row = F.struct(x["step"].alias("step"), c.alias("c"), acc["bound"].alias("bound"), fires.alias("fires"), F.when(fires, c + x["rel"]).alias("sz"))
        return F.struct(
            F.when(fires | x["flush"], F.lit(0).cast("long")).otherwise(c).alias("c"),
            F.when(fires, x["theta"] + x["thr"]).otherwise(acc["bound"]).alias("bound"),
            F.concat(acc["out"], F.array(row)).alias("out"),
        )

    folded = arrays.select("run", F.inline(F.aggregate("steps", start, turn, lambda a: a["out"])))
    folded = folded.withColumn("want", F.when(F.col("fires"), rounded(F.col("sz"))).otherwise(F.lit(0).cast("long")))
    return steps.drop("chk", "thr", "rel", "thr0").join(folded, ["run", "step"])


def threshold_sizes_grouped(steps: DataFrame) -> DataFrame:
    """The same rule as a grouped function: linear in a run's steps, for runs of very many."""
    steps = threshold_noise(steps)
    out = ["c", "bound", "fires", "sz", "want"]

    def fold(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("step")
        c, bound, made = 0, None, []
        for t, n, chk, thr, rel, theta, thr0, resets, every in zip(pdf.step, pdf.n_real, pdf.chk, pdf.thr, pdf.rel, pdf.theta, pdf.thr0, pdf.resets, pdf.purge_every, strict=True):
            bound = thr0 if bound is None else bound
            c += n
            fires = c + chk >= bound
            sz = c + rel if fires else None
            made.append((c, bound, bool(fires), sz, max(0, int((sz + 0.5) // 1)) if fires else 0))
            if fires:
                c, bound = 0, theta + thr
            elif resets and t % every == 0:
                c = 0
        return pdf.assign(**{k: [m[i] for m in made] for i, k in enumerate(out)})

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in steps.schema.fields), "c long, bound double, fires boolean, sz double, want long"])
    return steps.groupBy("run").applyInPandas(fold, schema).drop("chk", "thr", "rel", "thr0")


def buffer_depth(sized: DataFrame) -> DataFrame:
    """Adds deferred, real_out, dummy_out and the purge's columns: depth is a reflected walk inside a purge epoch."""
    epoch = F.floor((F.col("step") - 1) / F.col("purge_every")).cast("int")
    w = Window.partitionBy("run", "epoch").orderBy("step")
    d = sized.withColumn("epoch", epoch).withColumn("walk", F.sum(F.col("n_real") - F.col("want")).over(w))
    d = d.withColumn("depth", F.col("walk") - F.least(F.lit(0), F.min("walk").over(w)))
    d = d.withColumn("real_out", F.coalesce(F.lag("depth").over(w), F.lit(0)) + F.col("n_real") - F.col("depth"))
    d = d.withColumn("dummy_out", F.col("want") - F.col("real_out"))
    flush = F.col("step") % F.col("purge_every") == 0
    d = d.withColumn("purge_real", F.when(flush, F.least(F.col("depth"), F.col("purge_size"))).otherwise(0).cast("long"))
    d = d.withColumn("purge_dummy", F.when(flush, F.col("purge_size") - F.col("purge_real")).otherwise(0).cast("long"))
    d = d.withColumn("discarded", F.when(flush, F.col("depth") - F.col("purge_real")).otherwise(0).cast("long"))
    return d.withColumn("deferred", F.when(flush, F.lit(0)).otherwise(F.col("depth")).cast("long")).drop("walk")


def trace(sums: DataFrame, runs: Iterable[tuple[str, str, Params]]) -> DataFrame:
    """One row for each run and step: sizes, buffer and view after the step, answer, truth and error."""
    runs = list(runs)
    parts = []
    for strategy, sizes in (("interval", interval_sizes), ("threshold", threshold_sizes)):
        mine = [r for r in runs if r[1] == strategy]
        if mine:
            parts.append(sizes(with_runs(sums, mine)))
    sized = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1], allowMissingColumns=True)
    return series(buffer_depth(sized))


def series(d: DataFrame) -> DataFrame:
    w = per_run()
    d = d.withColumn("truth", F.sum("n_true").over(w)).withColumn("answer", F.sum(F.col("real_out") + F.col("purge_real")).over(w))
    d = d.withColumn("view_rows", F.sum(F.col("want") + F.when(F.col("step") % F.col("purge_every") == 0, F.col("purge_size")).otherwise(0)).over(w))
    return d.withColumn("l1", F.abs(F.col("truth") - F.col("answer")))


def quotas(traced: DataFrame) -> DataFrame:
    """run, epoch, release_step, lo, hi: real rows numbered (lo, hi] of an epoch leave the buffer at that step."""
    w = Window.partitionBy("run", "epoch").orderBy("step")
    out = F.col("real_out") + F.col("purge_real")
    q = traced.withColumn("hi", F.sum(out).over(w))
    return q.filter(out > 0).select("run", "epoch", F.col("step").alias("release_step"), (F.col("hi") - out).alias("lo"), "hi")


def place_rows(pairs: DataFrame, traced: DataFrame, purge_every: int, columns: list[str] | None = None) -> DataFrame:
    """Released rows with their release step, first in first out; rows that were never released are left out.

    ``pairs`` carry ord, their place in their step, and ``columns`` (of a view: key, l_rid, r_rid). Only offsets of
    steps are summed; no row is sorted globally.
    """
    w = Window.partitionBy("run", "epoch").orderBy("step").rowsBetween(Window.unboundedPreceding, -1)
    offsets = traced.select("run", "epoch", F.col("step").alias("born_step"), F.coalesce(F.sum("n_real").over(w), F.lit(0)).alias("before"))
    d = pairs.join(F.broadcast(offsets), "born_step").withColumn("place", F.col("before") + F.col("ord"))
    q = F.broadcast(quotas(traced))  # one row for each step at most
    on = (d["run"] == q["run"]) & (d["epoch"] == q["epoch"]) & (d["place"] > q["lo"]) & (d["place"] <= q["hi"])
    return d.join(q, on).select(d["run"], "born_step", *(columns or ["key", "l_rid", "r_rid"]), "release_step").withColumn("is_view", F.lit(True))


def dummy_rows(traced: DataFrame) -> DataFrame:
    """The view's dummies as rows, where a physical view is wanted."""
    n = F.col("dummy_out") + F.col("purge_dummy")
    return traced.filter(n > 0).select("run", F.col("step").alias("release_step"), F.explode(F.sequence(F.lit(1).cast("long"), n)).alias("k")).drop("k").withColumn("is_view", F.lit(False))
