"""Calendars: index -> instant. Regular ones are arithmetic and never stored; irregular ones are a small table."""

from __future__ import annotations

from dataclasses import dataclass
from datetime import datetime

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

SECONDS = {"second": 1, "minute": 60, "hour": 3600, "day": 86400, "week": 604800}


@dataclass(frozen=True)
class Calendar:
    """``n`` instants from ``origin`` in steps of ``unit``; ``unit`` "month" counts calendar months."""

    origin: datetime
    unit: str
    n: int | None = None

    @staticmethod
    def regular(start: datetime | str, unit: str, n: int | None = None) -> Calendar:
        if unit not in SECONDS and unit != "month":
            raise ValueError(f"unknown unit: {unit}")
        return Calendar(datetime.fromisoformat(start) if isinstance(start, str) else start, unit, n)

    @staticmethod
    def from_times(df: DataFrame, col: str) -> DataFrame:
        """An irregular calendar: the distinct instants of ``col`` in order, as (idx, t)."""
        days = df.select(F.col(col).alias("t")).where("t IS NOT NULL").distinct()
        return assign_index(days, ["t"], F.trunc("t", "year")).select("idx", "t")

    @staticmethod
    def spanning(df: DataFrame, col: str, unit: str) -> DataFrame:
        """(idx, t): the regular calendar from the unit that the first instant of ``col`` lies in to that of the last."""
        c = Calendar.regular("1970-01-05", unit)  # a Monday
        i = c.index_of(F.col(col))
        ends = df.agg(F.min(i).alias("lo"), F.max(i).alias("hi")).where("lo IS NOT NULL")
        return ends.select("lo", F.explode(F.sequence("lo", "hi")).alias("i")).select((F.col("i") - F.col("lo")).alias("idx"), c.instant(F.col("i")).alias("t"))

    @property
    def id(self) -> str:
        return f"{self.origin.isoformat()}/{self.unit}/{self.n}"

    def _origin(self) -> Column:
        return F.lit(self.origin.isoformat(sep=" ")).cast("timestamp_ntz")

    def index_of(self, t: Column) -> Column:
        """Index of the unit that an instant lies in."""
        t = t.cast("timestamp_ntz")
        if self.unit == "month":
            o = self.origin
            return ((F.year(t) - o.year) * 12 + F.month(t) - o.month).cast("long")
        micros = F.unix_micros(t.cast("timestamp")) - F.unix_micros(self._origin().cast("timestamp"))
        return F.floor(micros / F.lit(SECONDS[self.unit] * 1_000_000)).cast("long")

    def instant(self, idx: Column) -> Column:
        if self.unit == "month":
            return F.add_months(self._origin().cast("date"), idx.cast("int")).cast("timestamp_ntz")
        days, secs = divmod(SECONDS[self.unit], 86400)
        step = F.make_dt_interval(F.lit(0), F.lit(0), F.lit(0), F.lit(days * 86400 + secs).cast("decimal(18,6)"))
        return self._origin() + step * idx

    def frame(self, spark: SparkSession, n: int | None = None) -> DataFrame:
        """(idx, t), materialised."""
        size = n if n is not None else self.n
        if size is None:
            raise ValueError("an endless calendar can't be materialised")
        return spark.range(size).select(F.col("id").alias("idx"), self.instant(F.col("id")).alias("t"))

    def coarser(self, unit: str) -> Calendar:
        o = self.origin
        start = {
            "minute": o.replace(second=0, microsecond=0), "hour": o.replace(minute=0, second=0, microsecond=0),
            "day": o.replace(hour=0, minute=0, second=0, microsecond=0), "week": o,
            "month": o.replace(day=1, hour=0, minute=0, second=0, microsecond=0),
        }.get(unit, o)
        return Calendar(start, unit)


def unit_window(days: int, unit: str, hours_per_day: float = 8.5) -> int:
    """Entries in so many market days: by day, by (whole) hour or by minute of opening."""
    return {"day": days, "hour": days * int(hours_per_day), "minute": int(days * hours_per_day * 60)}[unit]


def assign_index(df: DataFrame, order: list[str], bucket: Column, first: int = 0) -> DataFrame:
    """A dense global ``idx`` in the given order, with no task seeing all rows.

    ``bucket`` must not decrease along the order (a day of the leading time, say). Rows are numbered inside their
    bucket; the counts of the buckets before are a table as long as there are buckets. Rows without a bucket come first."""
    keyed = df.withColumn("_b", bucket)
    counts = keyed.groupBy("_b").agg(F.count(F.lit(1)).alias("_n"))
    before = counts.select(F.col("_b").alias("_c"), (F.sum("_n").over(Window.orderBy("_b")) - F.col("_n")).alias("_before"))
    inside = F.row_number().over(Window.partitionBy("_b").orderBy(*order)).cast("long")
    return keyed.withColumn("_r", inside).join(before, F.col("_b").eqNullSafe(F.col("_c"))).withColumn("idx", F.col("_before") + F.col("_r") - 1 + first).drop("_b", "_c", "_r", "_before")
