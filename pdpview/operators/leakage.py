"""What an observer of sizes sees, and a simulator that needs only a private mechanism's output."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import noise
from ..params import Params
from ..plans.views import ViewSpec
from . import release


def transcript(sums: DataFrame, traced: DataFrame, spec: ViewSpec) -> DataFrame:
    """step, uploaded, cached, released, purged: the sizes of everything that this run moved in the open.

    Uploads are the private sides' batches as they were sent, cached what derive put into the buffer, released and
    purged what the release stage took out.
    """
    private = F.col("up_left") + (F.lit(0) if spec.right_public else F.col("up_right"))
    open_rows = sums.select("step", private.alias("uploaded"), F.col("n_padded").alias("cached"))
    moved = traced.select("step", (F.col("real_out") + F.col("dummy_out")).alias("released"), (F.col("purge_real") + F.col("purge_dummy")).alias("purged"))
    return open_rows.join(moved, "step")


def mech_interval(sums: DataFrame, p: Params) -> DataFrame:
    """step, v: noisy number of rows of the last interval at its end, else 0; straight from the derived data."""
    if p.purge_resets_counter or p.system_noise:
        raise ValueError("the mechanism is stated for hashed words and a counter that releases alone reset")
    w = Window.orderBy("step").rangeBetween(-(p.interval - 1), 0)
    z = noise.laplace(noise.joint_word(p.seed, "rel", F.col("step")), p.budget / p.eps)
    at = F.col("step") % p.interval == 0
    return sums.select("step", F.when(at, release.rounded(F.sum("n_real").over(w) + z)).otherwise(F.lit(0).cast("long")).alias("v"))


def mech_threshold(sums: DataFrame, p: Params) -> DataFrame:
    """step, v: the sparse-vector mechanism's outputs on the same data and noise."""
    sized = release.threshold_sizes_grouped(release.with_runs(sums, [("m", "threshold", p)]))
    return sized.select("step", F.col("want").alias("v"))


def simulate(mech: DataFrame, spec: ViewSpec) -> DataFrame:
    """The transcript, rebuilt from the mechanism's output and public parameters only: no data is read here."""
    p = spec.params
    if p.batch_cap is None:
        raise ValueError("a simulator needs the declared batch sizes: set batch_cap")
    batch = p.batch_cap[0] + (0 if spec.right_public else p.batch_cap[1])
    cached = F.lit(p.budget * batch) if p.pad_rule == "budget" else p.omega * batch * F.least(F.col("step"), F.lit(p.horizon))
    purge = F.when(F.col("step") % p.purge_every == 0, p.purge_size).otherwise(0).cast("long")
    return mech.select("step", F.lit(batch).cast("long").alias("uploaded"), cached.cast("long").alias("cached"), F.col("v").alias("released"), purge.alias("purged"))


def simulated_rows(sim: DataFrame, kind: str = "released") -> DataFrame:
    """Random words in place of the rows of each simulated batch."""
    return sim.filter(F.col(kind) > 0).select("step", F.explode(F.sequence(F.lit(1).cast("long"), kind)).alias("k")).select("step", F.floor(F.rand() * 4294967296).cast("long").alias("word"))
