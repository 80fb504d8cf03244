"""The padded buffer as rows: append, read real rows first, purge. For small buffers and tests of the count model."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def append(buffer: DataFrame, new: DataFrame) -> DataFrame:
    return buffer.unionByName(new, allowMissingColumns=True)


def read(buffer: DataFrame, size: int) -> tuple[DataFrame, DataFrame]:
    """(rows read, rest): real rows before dummies, oldest first; a read beyond the buffer adds fresh dummies."""
    w = Window.orderBy(F.col("is_view").desc(), "born_step", "ord")
    numbered = buffer.withColumn("__n", F.row_number().over(w))
    size = max(0, size)
    got = numbered.filter(F.col("__n") <= size).drop("__n")
    missing = max(0, size - buffer.count())
    if missing:
        fresh = buffer.sparkSession.range(missing).select(F.lit(False).alias("is_view"))
        got = got.unionByName(fresh, allowMissingColumns=True)
    return got, numbered.filter(F.col("__n") > size).drop("__n")


def write(buffer: DataFrame, path: str) -> None:
    """Appended rows by born step; a retried step replaces itself."""
    buffer.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("born_step").parquet(path)
