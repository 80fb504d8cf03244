"""What the text operators share: word pattern, row-wise Arrow mapping, folds, shared scratch space."""

from __future__ import annotations

import ctypes
import re
import sys
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

#: Words are runs of characters other than space and the ASCII controls tab to carriage return.
WORD = r"[^\x20\x09-\x0D]+"
WORDS = re.compile(WORD)


def words_of(text: str | None) -> list[str]:
    return WORDS.findall(text) if text else []


#: So many keys of a frame are treated as hot, if they have so many rows and the frame so many bytes; shares of each.
HOT_KEYS, HOT_ROWS, HOT_BYTES, SHARES = 500, 1000, 1 << 20, 64

_KEPT: dict[str, tuple[str, object]] = {}


def per_worker(kind: str, key: str, build: Callable[[], object]) -> object:
    """The object of this kind and key in this Python worker; it outlives a task, one of each kind is kept."""
    if _KEPT.get(kind, ("",))[0] != key:
        _KEPT[kind] = (key, build())
    return _KEPT[kind][1]


def give_back() -> None:
    """Returns freed memory of this Python worker to the system: workers live on between tasks, several an executor."""
    pa.default_memory_pool().release_unused()
    if sys.platform == "linux":
        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc only
        if trim is not None:
            trim(0)


def new_key() -> str:
    return uuid.uuid4().hex


def map_texts(
    df: DataFrame, columns: list[str], make: Callable[[], Callable[..., list]], schema: T.StructType | str, rows: int = 512
) -> DataFrame:
    """One narrow pass: ``make()`` runs once in each task and gives ``f(*column lists) -> list of row tuples``.

    At most ``rows`` input rows are held as Python objects at a time. Other columns of ``df`` are not read.
    """
    if isinstance(schema, str):
        schema = T._parse_datatype_string(schema)
    fields = [f.name for f in schema.fields]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        arrow = to_arrow_schema(schema)
        f = make()
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                part = batch.slice(at, rows)
                out = f(*(part.column(i).to_pylist() for i in range(part.num_columns)))
                if out:
                    cols = list(zip(*out, strict=True))
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(c, type=arrow.field(i).type) for i, c in enumerate(cols)], names=fields
                    )
        give_back()

    return df.select(*columns).mapInArrow(run, schema)


def filter_rows(df: DataFrame, columns: list[str], make: Callable[[], Callable[..., list[bool]]], rows: int = 512) -> DataFrame:
    """Rows of ``df``, all columns untouched, for which ``f(*column lists)`` says True. Narrow, no join."""
    where = [df.columns.index(c) for c in columns]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = make()
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                part = batch.slice(at, rows)
                keep = f(*(part.column(i).to_pylist() for i in where))
                if any(keep):
                    yield part.filter(pa.array(keep, pa.bool_()))
        give_back()

    return df.mapInArrow(run, df.schema)


def held_out(doc_id: Column) -> Column:
    """True for the evaluation fold: crc32 of the id's decimal text leaves 2 when divided by 4."""
    return F.coalesce(F.pmod(F.crc32(F.encode(doc_id.cast("string"), "UTF-8")), F.lit(4)) == 2, F.lit(False))


def shared_folder(spark: SparkSession, purpose: str) -> str:
    """A fresh path in the folder that driver and executors share (``spark.checkpoint.dir``)."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return f"{base.rstrip('/')}/{purpose}-{uuid.uuid4().hex}"


def stored(df: DataFrame, purpose: str) -> DataFrame:
    """``df`` written to the shared folder and read back: lineage ends, and a lost executor costs nothing."""
    path = shared_folder(df.sparkSession, purpose)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def hot_keys(df: DataFrame, key: str) -> list:
    """The most frequent keys of a frame, at most ``HOT_KEYS`` of them; small frames have none that matter."""
    if int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()) < HOT_BYTES:
        return []
    sizes = df.filter(F.col(key).isNotNull()).groupBy(key).agg(F.count("*").alias("k")).filter(F.col("k") >= HOT_ROWS)
    return [r[0] for r in sizes.orderBy(F.desc("k")).limit(HOT_KEYS).select(key).collect()]


def lookup(left: DataFrame, right: DataFrame, key: str, other: str, how: str = "inner", hot: list | None = None, hint: str | None = "merge") -> DataFrame:
    """``left`` with the columns of ``right``, which has one row for a key at most.

    Rows of ``left`` with a hot key (or none) are dealt out by the hash of the column ``other``, and a hot key's row of
    ``right`` is repeated for each share: no task meets such a key's rows alone.
    """
    hot = hot_keys(left, key) if hot is None else hot
    is_hot = F.col(key).isin(hot) if hot else F.lit(False)
    dealt = left.withColumn("__share", F.when(F.col(key).isNull() | is_hot, F.pmod(F.xxhash64(other), F.lit(SHARES))).otherwise(F.lit(0)).cast("int"))
    given = right.withColumn("__share", F.explode(F.when(is_hot, F.sequence(F.lit(0), F.lit(SHARES - 1))).otherwise(F.array(F.lit(0)))) if hot else F.lit(0))
    return dealt.join(given.hint(hint) if hint else given, [key, "__share"], how).drop("__share")


class Scratch:
    """Stored frames of one computation; ``with`` deletes their folders at its end, so nothing lazy may leave it."""

    def __init__(self, spark: SparkSession):
        self.spark, self.paths = spark, []

    def __call__(self, df: DataFrame, purpose: str) -> DataFrame:
        self.paths.append(shared_folder(self.spark, purpose))
        df.write.parquet(self.paths[-1])
        return self.spark.read.schema(df.schema).parquet(self.paths[-1])

    def drop_previous(self) -> None:
        """Deletes the frame stored before the last one: that of a round that is over."""
        self.delete(self.paths[-2])

    def delete(self, path: str) -> None:
        self.paths.remove(path)
        p = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(p, True)

    def __enter__(self) -> Scratch:
        return self

    def __exit__(self, *_) -> None:
        for path in list(self.paths):
            self.delete(path)
