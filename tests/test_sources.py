"""Sources and sinks: formats, partitioned views that can be written again, share folders, late rows, approximations."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from pdpview.catalog import QUERIES
from pdpview.functions import noise, shares
from pdpview.operators import buffer
from pdpview.plans import workloads as wl
from pdpview.plans.views import rewrite
from pdpview.sources.tables import EVENTS_SCHEMA, clean, load, write_share_folders, write_view
from pdpview.streaming.maintain import Maintainer


@pytest.mark.parametrize("form", ["parquet", "orc", "json", "csv"])
def test_formats(spark, small, tmp_path, form):
    e = load(spark, small, "events").select([f.name for f in EVENTS_SCHEMA.fields])
    path = str(tmp_path / form)
    exact = {"escape": '"', "timestampNTZFormat": "yyyy-MM-dd'T'HH:mm:ss.SSSSSS"}
    e.write.format(form).options(**exact).save(path)
    back = spark.read.schema(EVENTS_SCHEMA).format(form).options(**exact).load(path)
    assert back.exceptAll(e).count() == 0 and back.count() == e.count()


def test_view_sink_is_idempotent(spark, tmp_path):
    path = str(tmp_path / "v")
    v = spark.range(10).select("id", (F.col("id") % 3).cast("int").alias("release_step"), F.lit(True).alias("is_view"))
    write_view(v, path)
    write_view(v.filter("release_step = 1"), path)
    assert spark.read.parquet(path).count() == 10
    b = spark.range(4).select("id", F.lit(1).alias("born_step"), F.lit(True).alias("is_view"))
    buffer.write(b, str(tmp_path / "b"))
    buffer.write(b, str(tmp_path / "b"))
    assert spark.read.parquet(str(tmp_path / "b")).count() == 4
    assert buffer.append(b, b).count() == 8


def test_share_folders(spark, small, tmp_path):
    o = load(spark, small, "orders").select(F.col("o_orderkey").alias("rid"), "o_custkey")
    a, b = shares.split(F.col("o_custkey"), noise.hash_word("1", "s0", "x", F.col("rid")))
    x, y = (spark.read.parquet(f) for f in write_share_folders(o.select("rid", a.alias("share_0"), b.alias("share_1")), str(tmp_path), ["share_0", "share_1"]))
    back = x.join(y, "rid").select("rid", shares.recover(F.col("share_0"), F.col("share_1")).alias("o_custkey"))
    assert back.exceptAll(o).count() == 0


def test_clean_drops_nulls(spark):
    d = spark.createDataFrame([(1, None), (None, 2), (3, 4)], "a int, b int")
    assert [tuple(r) for r in clean(d, ["a", "b"]).collect()] == [(3, 4)]


def test_system_words_differ(spark):
    w = [tuple(r) for r in noise.system_words(spark, 20, ["rel"]).collect()]
    assert len(w) == 42 and len({r[3] for r in w}) > 35 and all(0 <= r[3] < 2**32 for r in w)


def test_late_rows_join_the_next_open_step(spark, small, tmp_path):
    m = Maintainer(spark, str(tmp_path / "m"), wl.W2M72, "interval", 36)
    e = load(spark, small, "events")
    m.batch(e.filter("ts < TIMESTAMP_NTZ '2024-01-10 00:00:00' AND event_id % 2 = 0"), 0)
    closed = m.last_closed()
    assert closed >= 4
    m.batch(e.filter("ts < TIMESTAMP_NTZ '2024-01-10 00:00:00' AND event_id % 2 = 1"), 1)
    late = m.table("rows", m.ROWS).filter("batch = 1")
    assert late.count() > 0 and late.agg(F.min("step")).first()[0] == closed + 1


def test_unregistered_views_are_rejected(spark):
    with pytest.raises(ValueError):
        rewrite(spark, "SELECT 1", wl.ViewSpec("none", None, None, 0, 1), spark.range(1), 1)


def test_approximations_are_close(spark, small):
    exact = {r.event_type: r.n for r in load(spark, small, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("n")).collect()}
    for r in QUERIES["agg_approx"].run(spark, small).collect():
        assert abs(r.users - exact[r.event_type]) <= max(1, 0.1 * exact[r.event_type])
