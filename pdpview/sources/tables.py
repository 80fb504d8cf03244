"""Tables as growing data: loading, cleaning, step assignment, surrogate ids, scratch storage."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Explicit schema of the event stream (streams never infer one).
EVENTS_SCHEMA = T.StructType(
    [
        T.StructField("event_id", T.LongType()),
        T.StructField("ts", T.TimestampNTZType()),
        T.StructField("user_id", T.LongType()),
        T.StructField("event_type", T.StringType()),
        T.StructField("value", T.DoubleType()),
        T.StructField("props", T.StringType()),
    ]
)

#: First day of the order tables and of the events (fixed values).
ORDERS_ORIGIN, EVENTS_ORIGIN = "1995-01-01", "2024-01-01"

#: All columns, a total order of the lines.
LINE_ORDER = ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus"]
#: Columns that tell the lines apart.
LINE_ID = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def clean(df: DataFrame, columns: list[str]) -> DataFrame:
    """Rows without a null in ``columns``."""
    return df.na.drop(subset=columns)


def step_of(time: Column, origin: str, days: int) -> Column:
    """Step number from 1 on: whole widths of ``days`` since the origin."""
    return (F.floor(F.datediff(F.to_date(time), F.lit(origin).cast("date")) / days) + 1).cast("int")


def step_of_hours(time: Column, origin: str, hours: int) -> Column:
    seconds = F.unix_timestamp(time.cast("timestamp")) - F.unix_timestamp(F.lit(origin).cast("timestamp"))
    return (F.floor(seconds / (3600 * hours)) + 1).cast("int")


def shared_folder(spark: SparkSession, purpose: str) -> str:
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return f"{base.rstrip('/')}/{purpose}-{uuid.uuid4().hex}"


def stored(df: DataFrame, purpose: str) -> DataFrame:
    """``df`` written once to the shared folder and read back; its lineage ends there."""
    path = shared_folder(df.sparkSession, purpose)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def surrogate_rid(df: DataFrame, order: list[str], name: str = "rid") -> DataFrame:
    """Consecutive ids from 1 in the order of ``order``, without a global window over rows.

    Rows are range-partitioned and sorted, stored once, and numbered inside their partition; each partition's
    offset comes from the partition counts alone.
    """
    place = F.monotonically_increasing_id()
    d = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__m", place)
    d = stored(d.withColumn("__p", F.shiftright("__m", 33)).withColumn("__i", F.col("__m").bitwiseAND((1 << 33) - 1)).drop("__m"), "rid")
    counts = d.groupBy("__p").agg(F.count("*").alias("__n"))
    offset = counts.select("__p", (F.sum("__n").over(Window.orderBy("__p")) - F.col("__n")).alias("__o"))
    return d.join(offset, "__p").withColumn(name, F.col("__o") + F.col("__i") + 1).drop("__p", "__i", "__o")


def write_view(view: DataFrame, path: str) -> None:
    """Released rows by release step; a repeated write of the same steps replaces them."""
    view.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("release_step").parquet(path)


def write_share_folders(df: DataFrame, path: str, shares: list[str]) -> list[str]:
    """Each server's share in a folder of its own, beside the row id."""
    folders = []
    for k, c in enumerate(shares):
        folders.append(f"{path}/server_{k}")
        df.select("rid", c).write.mode("overwrite").parquet(folders[-1])
    return folders
