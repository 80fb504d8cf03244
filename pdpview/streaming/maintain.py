"""Maintenance of a private x public view over a stream, one micro-batch after another.

Rows arrive by event time; a step closes when the watermark has passed its end. For every closed step the derive
stage reads the new step and the horizon before it, the counter and the threshold state are taken from a small state
table, and a release command is made; a purge first moves its public number of rows into the view. Noise is drawn
once for each (step, purpose) and stored before it is used, so that a replayed batch releases the same sizes again. All
tables are written by step with dynamic overwrite, which makes a replay idempotent.

Closing a step reads the private rows of its horizon and the public rows since the oldest of them alone (folders of
other steps are pruned), and how far time has come is kept as one row a batch. A row that comes again within the
horizon is one row; the source must not send it again later, when its first copy is read no more.
"""

from __future__ import annotations

import math
import os
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import noise
from ..operators import derive
from ..params import Params
from ..plans.views import ViewSpec
from ..sources.tables import EVENTS_ORIGIN, EVENTS_SCHEMA, step_of_hours

STATE = "step int, n_real long, c long, bound double, depth long, fires boolean, want long, real_out long, purge_real long, purge_dummy long, discarded long"
CLOCK = "batch long, newest timestamp"


def event_stream(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS_SCHEMA).option("maxFilesPerTrigger", per_trigger).parquet(path)


@dataclass
class Maintainer:
    """Folders under ``root``: rows (uploads by step), pairs (view rows by born step), state (one row a step)."""

    spark: SparkSession
    root: str
    spec: ViewSpec
    strategy: str
    step_hours: int
    lateness_hours: int = 1

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def table(self, name: str, schema: str) -> DataFrame:
        return self.spark.read.schema(schema).parquet(self.path(name))

    def has(self, name: str) -> bool:
        jvm = self.spark._jvm
        p = jvm.org.apache.hadoop.fs.Path(self.path(name))
        return p.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(p)

    def put(self, df: DataFrame, name: str, *by: str) -> None:
        df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(*by).parquet(self.path(name))

    PAIRS = "born_step int, key long, l_rid long, r_rid long, ord long, step int"
    ROWS = "side string, rid long, key long, day timestamp, batch long, step int"

    def batch(self, rows: DataFrame, batch_id: int) -> None:
        """One micro-batch: store its rows, then close every step that the watermark has passed."""
        kinds = F.when(F.col("event_type") == "error", "L").when(F.col("event_type") == "purchase", "R")
        r = rows.select(kinds.alias("side"), F.col("event_id").alias("rid"), F.col("user_id").alias("key"), F.col("ts").cast("timestamp").alias("day"), F.lit(batch_id).cast("long").alias("batch"))
        closed = self.last_closed()
        # a late row goes into the next open step: owners upload what has come since their last upload
        step = F.greatest(step_of_hours(F.col("day"), EVENTS_ORIGIN, self.step_hours), F.lit(closed + 1))
        if not self.has(f"rows/batch={batch_id}"):  # a replay keeps the steps that the rows were given first
            self.put(r.filter("side IS NOT NULL").agg(F.max("day").alias("newest")).withColumn("batch", F.lit(batch_id).cast("long")), "clock", "batch")
            self.put(r.filter("side IS NOT NULL").withColumn("step", step), "rows", "batch", "step")
        newest = self.table("clock", CLOCK).agg(F.max("newest")).first()[0]
        if newest is None:
            return
        open_at = self.spark.range(1).select(step_of_hours(F.lit(newest) - F.expr(f"INTERVAL {self.lateness_hours} HOURS"), EVENTS_ORIGIN, self.step_hours).alias("s")).first()["s"]
        for t in range(closed + 1, open_at):
            self.close(t)

    def last_closed(self) -> int:
        return (self.table("state", STATE).agg(F.max("step")).first()[0] or 0) if self.has("state") else 0

    def close(self, t: int) -> None:
        sides = []
        for s, first in (("L", t - self.spec.params.horizon + 1), ("R", None)):
            if first is None:  # no partner of an active row is older than that row; a late row may meet earlier steps
                oldest = sides[0].agg(F.min("day")).first()[0]
                first = t if oldest is None else self.spark.range(1).select(step_of_hours(F.lit(oldest), EVENTS_ORIGIN, self.step_hours).alias("s")).first()["s"]
            d = self.table("rows", self.ROWS).filter((F.col("side") == s) & (F.col("step") <= t) & (F.col("step") >= first))
            sides.append(d.groupBy("rid").agg(F.min(F.struct("step", "key", "day")).alias("x")).select("rid", "x.key", "x.day", "x.step"))
        pairs = derive.numbered(derive.increment(replace(self.spec, span=None), *sides, t))
        self.put(pairs.withColumn("step", F.lit(t)), "pairs", "step")
        n = self.table("pairs", self.PAIRS).filter(F.col("step") == t).count()
        before = self.table("state", STATE).filter(F.col("step") == t - 1).first() if t > 1 and self.has("state") else None
        self.put(self.spark.createDataFrame([self.advance(t, n, before)], STATE), "state", "step")

    def words(self, t: int) -> dict[str, float]:
        """Stored noise of a step: drawn at most once."""
        name = f"noise/step={t}"
        if not self.has(name):
            p = self.spec.params
            if p.system_noise:
                import secrets

                z = {k: secrets.randbits(32) ^ secrets.randbits(32) for k in ("chk", "rel", "thr")}
            else:
                cols = [noise.joint_word(p.seed, k, F.lit(t)).alias(k) for k in ("chk", "rel", "thr")]
                z = self.spark.range(1).select(*cols).first().asDict()
            self.spark.createDataFrame([(z["chk"], z["rel"], z["thr"])], "chk long, rel long, thr long").write.mode("overwrite").parquet(self.path(name))
        return self.spark.read.schema("chk long, rel long, thr long").parquet(self.path(name)).first().asDict()

    def advance(self, t: int, n: int, before) -> tuple:
        """The state after step ``t``, by the same rule as ``release.trace``: check and release, then the purge."""
        p: Params = self.spec.params
        z, scale = self.words(t), p.budget / p.eps
        if before is None:
            c, depth = 0, 0
            bound = p.theta + noise.laplace_value(self.words(0)["thr"], 4 * scale)
        else:
            reset = p.purge_resets_counter and before.step % p.purge_every == 0
            c, depth = (0 if before.fires or reset else before.c), before.depth
            bound = before.bound
            if before.fires:
                bound = p.theta + noise.laplace_value(self.words(t - 1)["thr"], 4 * scale)
        c, depth = c + n, depth + n
        if self.strategy == "interval":
            fires, rel = t % p.interval == 0, scale
        else:
            fires, rel = c + noise.laplace_value(z["chk"], 8 * scale) >= bound, (4 if p.scale_release == "mechanism" else 2) * scale
        want = max(0, math.floor(c + noise.laplace_value(z["rel"], rel) + 0.5)) if fires else 0
        out = min(want, depth)
        depth -= out
        saved = dummies = lost = 0
        if t % p.purge_every == 0:
            saved = min(depth, p.purge_size)
            dummies, lost, depth = p.purge_size - saved, depth - saved, 0
        return t, n, c, bound, depth, bool(fires), want, out, saved, dummies, lost

    def run(self, path: str, checkpoint: str | None = None) -> DataFrame:
        """Consumes what is there and returns the state table."""
        q = (
            event_stream(self.spark, path)
            .writeStream.foreachBatch(self.batch)
            .option("checkpointLocation", checkpoint or os.path.join(self.root, "checkpoint"))
            .trigger(availableNow=True)
            .start()
        )
        q.awaitTermination()
        return self.table("state", STATE)
