"""Upload steps: per-step counts and padding of batches to a public size."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def all_steps(df: DataFrame, last: int) -> DataFrame:
    """step 1..last, empty steps included."""
    return df.sparkSession.range(1, last + 1).select(F.col("id").cast("int").alias("step"))


def batch_sizes(side: DataFrame) -> DataFrame:
    return side.groupBy("step").agg(F.count("*").alias("n"))


def pad_counted(side: DataFrame, cap: int | None = None) -> DataFrame:
    """step, n_rows, n_dummy, n_total: dummies as a number. Without ``cap`` the public size is the largest batch."""
    b = batch_sizes(side)
    size = b.agg(F.max("n").alias("cap")) if cap is None else None
    b = b.crossJoin(F.broadcast(size)) if size is not None else b.withColumn("cap", F.lit(cap).cast("long"))
    return b.select("step", F.col("n").alias("n_rows"), F.greatest(F.col("cap") - F.col("n"), F.lit(0)).alias("n_dummy"), F.greatest("cap", "n").alias("n_total"))


def pad_physical(side: DataFrame, cap: int | None = None) -> DataFrame:
    """The rows with ``is_real`` and, in each step, dummy rows (null contents) up to the public size."""
    dummies = pad_counted(side, cap).filter("n_dummy > 0").select("step", F.explode(F.sequence(F.lit(1).cast("long"), "n_dummy")).alias("__k")).drop("__k")
    return side.withColumn("is_real", F.lit(True)).unionByName(dummies.withColumn("is_real", F.lit(False)), allowMissingColumns=True)
