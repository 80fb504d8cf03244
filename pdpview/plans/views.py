"""View definitions, registration and query rewriting."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..params import Params


@dataclass(frozen=True)
class ViewSpec:
    """An equi-join of two growing tables with a bounded lag; ``right_public`` sides carry no budget.

    Sides have the columns rid, key, day (DATE or TIMESTAMP), step. ``lag_unit`` 'step' compares steps, 'day' days.
    ``span`` is how many steps the right row of a pair may come after the left one (never before it); with it, pairs
    are looked for among neighbouring steps of a key only, not in the key's whole history.
    """

    name: str
    left: Callable[[SparkSession, str], DataFrame]
    right: Callable[[SparkSession, str], DataFrame]
    lag_lo: int | None
    lag_hi: int
    lag_unit: str = "step"
    right_public: bool = False
    span: int | None = None
    params: Params = field(default_factory=Params)
    steps_sql: dict[str, str] = field(default_factory=dict)

    def lag_ok(self, l: str = "l", r: str = "r"):  # noqa: E741
        if self.lag_unit == "step":
            lag = F.col(f"{r}.step") - F.col(f"{l}.step")
        elif self.lag_unit == "hour":
            lag = (F.unix_micros(F.col(f"{r}.day").cast("timestamp")) - F.unix_micros(F.col(f"{l}.day").cast("timestamp"))) / 3.6e9
        else:
            lag = F.datediff(F.col(f"{r}.day"), F.col(f"{l}.day"))
        ok = lag <= self.lag_hi
        return ok if self.lag_lo is None else (lag >= self.lag_lo) & ok

    @property
    def is_pure_equi(self) -> bool:
        """Whether key and step alone decide on a pair, so that truncation has a closed form on two private sides."""
        return self.lag_unit == "step" and self.lag_lo == 0 and self.lag_hi == self.params.horizon - 1


REGISTERED: dict[str, ViewSpec] = {}


def register(spec: ViewSpec) -> ViewSpec:
    """Fixes a view before data or queries come."""
    REGISTERED[spec.name] = spec
    return spec


def rewrite(spark: SparkSession, sql: str, spec: ViewSpec, view: DataFrame, at_step: int) -> DataFrame:
    """The query over the registered view's name, answered from released real rows up to ``at_step`` alone."""
    if spec.name not in REGISTERED:
        raise ValueError(f"{spec.name} is not a registered view")
    view.filter((F.col("release_step") <= at_step) & F.col("is_view")).createOrReplaceTempView(spec.name)
    return spark.sql(sql)
