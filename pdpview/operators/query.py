"""Answers from the released view alone."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def answer(view: DataFrame, at_step: int, *aggs: Column, by: list[str] | None = None, buffer: DataFrame | None = None) -> DataFrame:
    """Aggregates over the view's real rows up to ``at_step``; ``buffer`` adds the rows not yet released (costly)."""
    rows = view.filter((F.col("release_step") <= at_step) & F.col("is_view"))
    if buffer is not None:
        rows = rows.unionByName(buffer.filter((F.col("born_step") <= at_step) & F.col("is_view")), allowMissingColumns=True)
    aggs = aggs or (F.count("*").alias("answer"),)
    return rows.groupBy(*by).agg(*aggs) if by else rows.agg(*aggs)
