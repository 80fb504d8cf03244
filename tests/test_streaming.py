"""Streams give what the batch form gives, and a replay changes nothing."""

from __future__ import annotations

from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from pdpview.operators import derive, release
from pdpview.plans import workloads as wl
from pdpview.sources.tables import load
from pdpview.streaming import windows
from pdpview.streaming.maintain import Maintainer, event_stream


@pytest.fixture(scope="module")
def files(spark, small, tmp_path_factory):
    """The events in four files by time."""
    path = str(tmp_path_factory.mktemp("events"))
    e = load(spark, small, "events")
    for k in range(4):
        day = F.dayofmonth("ts")
        e.filter((day > 8 * k) & (day <= 8 * (k + 1))).coalesce(1).write.mode("append").parquet(path)
    return path


def drained(q):
    q.processAllAvailable()
    q.stop()


def test_windows_and_dedup(spark, small, files, tmp_path):
    q = windows.deduplicated(event_stream(spark, files)).writeStream.format("memory").queryName("dedup").option("checkpointLocation", str(tmp_path / "a")).start()
    drained(q)
    assert spark.table("dedup").count() == load(spark, small, "events").count()
    q = windows.window_counts(event_stream(spark, files)).writeStream.outputMode("append").format("memory").queryName("counts").option("checkpointLocation", str(tmp_path / "b")).start()
    drained(q)
    batch = load(spark, small, "events").withColumn("t", F.col("ts").cast("timestamp")).groupBy(F.window("t", "12 hours"), "event_type").count()
    closed = spark.table("counts")
    assert 0 < closed.count() <= batch.count()
    assert closed.select("window", "event_type", "n").exceptAll(batch).count() == 0


def test_interval_join(spark, small, files, tmp_path):
    q = windows.interval_join(event_stream(spark, files), event_stream(spark, files)).writeStream.format("memory").queryName("pairs").option("checkpointLocation", str(tmp_path / "c")).start()
    drained(q)
    e = load(spark, small, "events")
    a, b = e.filter("event_type = 'error'").alias("a"), e.filter("event_type = 'purchase'").alias("b")
    n = a.join(b, (F.col("a.user_id") == F.col("b.user_id")) & (F.col("b.ts") >= F.col("a.ts")) & (F.col("b.ts") <= F.col("a.ts") + F.expr("INTERVAL 24 HOURS"))).count()
    assert spark.table("pairs").count() == n


@pytest.mark.parametrize(("strategy", "changes"), [("interval", {}), ("threshold", {}), ("interval", {"purge_every": 4, "purge_size": 6}), ("threshold", {"purge_every": 4, "purge_size": 6, "purge_resets_counter": True, "eps": 20.0})])
def test_maintained_view_equals_batch(spark, small, files, tmp_path, strategy, changes):
    spec = replace(wl.W2M72, params=wl.W2M72.params.but(**changes))
    m = Maintainer(spark, str(tmp_path / "m"), spec, strategy, 36)
    state = {r.step: r for r in m.run(files).collect()}
    t = release.trace(derive.summaries(spec, *wl.sides(spec, spark, small)), [("x", strategy, spec.params)]).orderBy("step").collect()
    assert len(state) >= 15
    for r in t[: len(state)]:
        s = state[r.step]
        assert (s.n_real, s.c, s.fires, s.want, s.real_out) == (r.n_real, r.c, r.fires, r.want, r.real_out)
        assert (s.purge_real, s.purge_dummy, s.discarded, s.depth) == (r.purge_real, r.purge_dummy, r.discarded, r.deferred)
    assert not changes or sum(s.purge_real for s in state.values()) > 0
    again = m.spark.read.parquet(files).limit(0)
    m.batch(load(spark, small, "events").filter(F.dayofmonth("ts") <= 8), 0)  # a replayed first batch
    assert {r.step: (r.step, r.n_real, r.c, r.want) for r in m.table("state", "step int, n_real long, c long, want long").collect()} == {k: (r.step, r.n_real, r.c, r.want) for k, r in state.items()}
    assert again.count() == 0


def test_stateful_threshold_equals_batch(spark, small, tmp_path):
    spec = wl.W2M72
    sums = derive.summaries(spec, *wl.sides(spec, spark, small))
    p = spec.params
    from pdpview.functions import noise

    words = sums.select(F.lit("v").alias("view"), "step", "n_real", *(noise.joint_word(p.seed, k, F.col("step")).alias(k) for k in ("chk", "rel", "thr")), noise.joint_word(p.seed, "thr", F.lit(0)).alias("thr0"))
    path = str(tmp_path / "steps")
    words.coalesce(1).write.parquet(path)
    stream = spark.readStream.schema(words.schema).parquet(path)
    q = windows.threshold_releases(stream, p).writeStream.outputMode("append").format("memory").queryName("cmds").option("checkpointLocation", str(tmp_path / "d")).start()
    drained(q)
    want = release.threshold_sizes(release.with_runs(sums, [("v", "threshold", p)])).select(F.col("run").alias("view"), "step", "c", "fires", "want")
    assert sorted(map(tuple, spark.table("cmds").collect())) == sorted(map(tuple, want.collect()))
