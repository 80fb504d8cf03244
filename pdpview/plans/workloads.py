"""The experiment workloads on the given tables, their sides and parameter sweeps."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..params import Params
from ..sources.tables import EVENTS_ORIGIN, LINE_ID, ORDERS_ORIGIN, clean, load, step_of, step_of_hours
from .views import ViewSpec, register


def orders_side(days: int):
    def side(spark: SparkSession, sf_dir: str) -> DataFrame:
        o = clean(load(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate"), ["o_orderkey", "o_orderdate"])
        return o.select(F.col("o_orderkey").alias("rid"), F.col("o_orderkey").alias("key"), F.to_date("o_orderdate").alias("day"), step_of(F.col("o_orderdate"), ORDERS_ORIGIN, days).alias("step"))

    return side


def row_word(*columns: str) -> Column:
    """60 bits of a row's content as its id: no window and no sort; rows equal in these columns share an id."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *(F.col(c).cast("string") for c in columns))), 1, 15), 16, 10).cast("long")


def lines_side(key: str, flag: str | None, days: int, *more: str):
    """Lines of one return flag, or of all; ``more`` columns go along."""

    def side(spark: SparkSession, sf_dir: str) -> DataFrame:
        d = clean(load(spark, sf_dir, "lineitem"), [key, "l_shipdate", "l_returnflag"])
        d = d if flag is None else d.filter(F.col("l_returnflag") == flag)
        return d.select(row_word(*LINE_ID).alias("rid"), F.col(key).alias("key"), F.to_date("l_shipdate").alias("day"), step_of(F.col("l_shipdate"), ORDERS_ORIGIN, days).alias("step"), *more)

    return side


def events_side(kind: str, hours: int):
    def side(spark: SparkSession, sf_dir: str) -> DataFrame:
        e = clean(load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type"), ["event_id", "ts", "user_id"])
        return e.filter(F.col("event_type") == kind).select(F.col("event_id").alias("rid"), F.col("user_id").alias("key"), F.col("ts").alias("day"), step_of_hours(F.col("ts"), EVENTS_ORIGIN, hours).alias("step"))

    return side


RETURNS = Params(omega=1, budget=10, interval=10, theta=30)
AWARDS = Params(omega=10, budget=20, interval=3, theta=30)

W1 = register(ViewSpec("w1", orders_side(1), lines_side("l_orderkey", "R", 1), 0, 10, span=10, params=RETURNS))
W1D = register(ViewSpec("w1d", orders_side(1), lines_side("l_orderkey", None, 1), 0, 9, span=9, params=RETURNS))
W1W = register(ViewSpec("w1w", orders_side(10), lines_side("l_orderkey", "R", 10), 0, 9, span=9, params=RETURNS))
W2 = register(ViewSpec("w2", lines_side("l_partkey", "R", 5), lines_side("l_partkey", "A", 5), 0, 10, "day", True, 2, AWARDS))
W2B30 = register(replace(W2, name="w2b30", params=AWARDS.but(budget=30)))
W2SB30 = register(replace(W2, name="w2sb30", left=lines_side("l_suppkey", "R", 5), right=lines_side("l_suppkey", "A", 5), params=AWARDS.but(budget=30)))
W2S = register(ViewSpec("w2s", lines_side("l_suppkey", "R", 5), lines_side("l_suppkey", "A", 5), 0, 10, "day", True, 2, AWARDS))


def w2m(hours: int, step_hours: int, omega: int, times: int = 2) -> ViewSpec:
    """Errors followed by purchases of the same user within ``hours``."""
    p = Params(omega=omega, budget=times * omega, interval=1 if step_hours > 100 else 3, theta=30)
    return ViewSpec(f"w2m_{hours}", events_side("error", step_hours), events_side("purchase", step_hours), 0, hours, "hour", True, -(-hours // step_hours), p)


W2M240, W2M72, W2M24 = (register(w2m(*x)) for x in ((240, 120, 10), (72, 36, 8), (24, 12, 4)))


def sides(spec: ViewSpec, spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    return spec.left(spark, sf_dir), spec.right(spark, sf_dir)


def sparse(side: DataFrame) -> DataFrame:
    """About a tenth of the rows, chosen by hash bits of key and rid."""
    word = F.conv(F.substring(F.md5(F.concat_ws("|", "key", "rid")), 1, 8), 16, 10).cast("long")
    return side.filter(word % 10 == 0)


def burst(side: DataFrame, copies: int = 2, offset: int = 1 << 40) -> DataFrame:
    """Every row ``copies`` times under new keys, on both sides alike, so twice the view rows come at each step."""
    k = F.explode(F.sequence(F.lit(0), F.lit(copies - 1)))
    return side.withColumn("__k", k).withColumn("key", F.col("key") + F.col("__k") * F.lit(offset)).drop("__k")


def half(side: DataFrame) -> DataFrame:
    """The rows of about half of the keys, so that pairs stay whole."""
    return side.filter(F.conv(F.substring(F.md5(F.col("key").cast("string")), 1, 8), 16, 10).cast("long") % 2 == 0)


#: Values of the sweeps (fixed values).
EPS_SWEEP = (0.01, 0.05, 0.1, 0.5, 1.0, 1.5, 5.0, 10.0, 50.0)
OMEGA_SWEEP = (2, 4, 8, 16, 32)
T_SWEEP = (1, 2, 5, 10, 20, 50, 100)
