"""What the private strategies are compared with; all on the step summaries' columns."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import noise
from ..params import Params
from ..plans.views import ViewSpec
from . import derive, release


def by_step():
    return Window.orderBy("step")


def nm(sums: DataFrame) -> DataFrame:
    """No materialization: exact answers, each query joins all padded rows so far again."""
    scanned = F.sum(F.col("up_left") + F.col("up_right")).over(by_step())
    truth = F.sum("n_true").over(by_step())
    return sums.select("step", truth.alias("truth"), truth.alias("answer"), F.lit(0).cast("long").alias("view_rows"), scanned.alias("scanned_rows"))


def nm_query(spec: ViewSpec, left: DataFrame, right: DataFrame, t: int) -> DataFrame:
    """The recomputed query itself at step ``t``: one row ``answer``."""
    upto = lambda d: d.filter(F.col("step") <= t)
    return derive.true_pairs(spec, upto(left), upto(right)).agg(F.count("*").alias("answer"))


def ep(sums: DataFrame, truncate: bool = True) -> DataFrame:
    """Exhaustive padding: every step's padded output goes to the view at once. Untruncated, it loses nothing."""
    rows = F.sum("n_padded").over(by_step())
    answer = F.sum("n_real" if truncate else "n_true").over(by_step())
    return sums.select("step", F.sum("n_true").over(by_step()).alias("truth"), answer.alias("answer"), rows.alias("view_rows"), rows.alias("scanned_rows"))


def otm(sums: DataFrame, built_at: int = 0) -> DataFrame:
    """One-time view: built at the start, never updated."""
    old = F.sum(F.when(F.col("step") <= built_at, F.col("n_real")).otherwise(0)).over(by_step())
    return sums.select("step", F.sum("n_true").over(by_step()).alias("truth"), old.alias("answer"), old.alias("view_rows"), old.alias("scanned_rows"))


def immediate(sums: DataFrame) -> DataFrame:
    """Unpadded synchronization: the transcript shows every step's exact number of new rows."""
    return sums.select("step", F.col("n_real").alias("observed_rows"))


def one_shot(sums: DataFrame, p: Params) -> DataFrame:
    """Pad then shrink once: a single noisy resize of a static database; one row."""
    z = noise.laplace(noise.joint_word(p.seed, "once", F.lit(0)), p.budget / p.eps)
    total = sums.agg(F.sum("n_real").alias("c"))
    return total.select("c", release.rounded(F.col("c") + z).alias("view_rows"), F.least("c", release.rounded(F.col("c") + z)).alias("answer"))


def owner_sync_nm(uploads: DataFrame, sums: DataFrame) -> DataFrame:
    """Owners upload privately, each query joins all uploaded rows again: uploaded and scanned rows by step."""
    w = Window.orderBy("step")
    return uploads.join(sums.select("step", "n_right"), "step").select("step", F.sum("want").over(w).alias("uploaded_rows"), F.sum(F.col("want") + F.col("n_right")).over(w).alias("scanned_rows"))
