"""Truncation: no input row changes the number of new view rows by more than omega.

The closed form of the scanning sort-merge join: in a group of n1 left and n2 right rows, left row i meets right
row j exactly if both lie in the same block of omega rows. Two rankings and an equi-join on the block do it: a heavy
key is ranked in parts and then falls apart into blocks.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


#: Groups of more rows are ranked in parts, of which they have ``PARTS``; ids are cut into parts by their top bits.
HOT_GROUP, PARTS = 1 << 24, 256


def ranked(side: DataFrame, group: list[str], order: list[str], name: str, hot_group: int = HOT_GROUP) -> DataFrame:
    """``side`` with ``name``, a row's place (from 1) in its group by ``order``, whose last column is an id.

    Rows of a hot group are ranked inside parts of the group, ranges of the id under equal leading order columns; a
    part's offset comes from one count for each part. A table of N rows has N / ``hot_group`` hot groups at most, so
    what is broadcast has a bound; other groups are ranked whole.
    """
    *lead, rid = order
    hot = side.groupBy(*group).agg(F.count("*").alias("__n"), F.min(rid).alias("__lo"), F.max(rid).alias("__hi")).filter(F.col("__n") > hot_group).drop("__n")
    d = side.join(F.broadcast(hot), group, "left")
    width = F.floor((F.col("__hi") - F.col("__lo")) / PARTS) + 1
    d = d.withColumn("__part", F.coalesce(F.floor((F.col(rid) - F.col("__lo")) / width), F.lit(0))).withColumn("__hot", F.col("__lo").isNotNull())
    keys = [*group, *(F.when(F.col("__hot"), F.col(c)) for c in lead), "__part"]
    d = d.withColumn("__i", F.row_number().over(Window.partitionBy(*keys).orderBy(*order)))
    sizes = d.filter("__hot").groupBy(*group, *lead, "__part").agg(F.count("*").alias("__n"))
    upto = Window.partitionBy(*group).orderBy(*lead, "__part")
    before = sizes.withColumn("__before", F.sum("__n").over(upto) - F.col("__n")).drop("__n")
    return d.join(before, [*group, *lead, "__part"], "left").withColumn(name, F.col("__i") + F.coalesce("__before", F.lit(0))).drop("__lo", "__hi", "__part", "__hot", "__i", "__before")


def with_block(side: DataFrame, group: list[str], order: list[str], omega: int, hot_group: int | None = None) -> DataFrame:
    if hot_group is None:
        side = side.withColumn("__rank", F.row_number().over(Window.partitionBy(*group).orderBy(*order)))
    else:
        side = ranked(side, group, order, "__rank", hot_group)
    return side.withColumn("block", F.floor((F.col("__rank") - 1) / omega).cast("long")).drop("__rank")


def merge_join(left: DataFrame, right: DataFrame, group: list[str], left_order: list[str], right_order: list[str], omega: int, hot_group: int | None = None) -> DataFrame:
    """Pairs of the truncated equi-join; columns of the two sides other than ``group`` must differ in name.

    ``hot_group`` (say ``HOT_GROUP``): groups of more rows are ranked in parts, for one more count and join of the rows.
    """
    return with_block(left, group, left_order, omega, hot_group).join(with_block(right, group, right_order, omega, hot_group), [*group, "block"])


def cap_private(pairs: DataFrame, invocation: list[str], order: list[str], omega: int) -> DataFrame:
    """Private with public rows: each private row keeps its first omega partners of an invocation; any predicate."""
    return pairs.withColumn("__k", F.row_number().over(Window.partitionBy(*invocation).orderBy(*order))).filter(F.col("__k") <= omega).drop("__k")


def oblivious_filter(df: DataFrame, keep) -> DataFrame:
    """All rows stay, failing ones become dummies: the length tells nothing (1-stable)."""
    return df.withColumn("is_view", F.coalesce(keep, F.lit(False)))


def greedy(candidates: pd.DataFrame, omega: int) -> pd.DataFrame:
    """Scan order: a pair is kept if both rows have kept fewer than omega before."""
    used_l: dict = {}
    used_r: dict = {}
    keep = []
    for a, b in zip(candidates["l_rid"], candidates["r_rid"], strict=True):
        ok = used_l.get(a, 0) < omega and used_r.get(b, 0) < omega
        if ok:
            used_l[a] = used_l.get(a, 0) + 1
            used_r[b] = used_r.get(b, 0) + 1
        keep.append(ok)
    return candidates[keep]


def scan(pairs: DataFrame, group: list[str], omega: int) -> DataFrame:
    """The two-phase form: a full join's pairs, scanned group by group with the greedy rule.

    For predicates without a closed form: whether a pair stays depends on all pairs before it, so a group, one
    (invocation, key), is walked in one task and its pairs must fit there.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        return greedy(pdf.sort_values(["r_rid", "l_rid"], kind="stable"), omega)

    return pairs.groupBy(*group).applyInPandas(run, pairs.schema)


def theta_join(left: DataFrame, right: DataFrame, group: list[str], predicate: Callable, omega: int) -> DataFrame:
    """Truncated nested-loop join: ``predicate`` decides inside groups of equal ``group`` columns (range buckets)."""
    pairs = left.alias("l").join(right.alias("r"), group).filter(predicate())
    return scan(pairs, group, omega)


def max_contribution(pairs: DataFrame, by: list[str]) -> DataFrame:
    """One row ``most``: the largest number of pairs of one row."""
    return pairs.groupBy(*by).agg(F.count("*").alias("k")).agg(F.max("k").alias("most"))
