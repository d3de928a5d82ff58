"""SeriesFrame: many calendar series in one DataFrame (series_id, idx, v), one row per entry that isn't empty."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import nulls
from .calendar import Calendar

AGGREGATES: dict[str, Callable[[Column, Column], Column]] = {
    "sum": lambda v, t: F.sum(v), "avg": lambda v, t: F.avg(v), "min": lambda v, t: F.min(v), "max": lambda v, t: F.max(v),
    "count": lambda v, t: F.count(v).cast("double"), "first": lambda v, t: F.min_by(v, t), "last": lambda v, t: F.max_by(v, t),
}


@dataclass(frozen=True)
class SeriesFrame:
    """Series on one calendar. A missing row or a NULL is an empty entry, NaN an unknown one.

    ``seg`` columns are added by ``plans.segments``; window operators partition by them when they are there."""

    df: DataFrame
    calendar: Calendar
    name: str = "series"
    #: Entries of a segment with its halo, where the frame is cut.
    seg_length: int | None = None

    # ---- construction -------------------------------------------------------------------------------------------------

    @staticmethod
    def of(df: DataFrame, key: Column | str | None, time: str, value: Column | str, calendar: Calendar, agg: str = "avg", name: str = "series") -> SeriesFrame:
        """Group rows by key and calendar entry; several values of an entry become one by ``agg``."""
        k = F.lit(name) if key is None else (F.col(key) if isinstance(key, str) else key)
        v = F.col(value) if isinstance(value, str) else value
        rows = df.select(k.cast("string").alias("series_id"), calendar.index_of(F.col(time)).alias("idx"), v.cast("double").alias("v"), F.col(time).alias("_t"))
        return SeriesFrame(rows.groupBy("series_id", "idx").agg(AGGREGATES[agg](F.col("v"), F.col("_t")).alias("v")), calendar, name)

    def with_df(self, df: DataFrame, name: str | None = None) -> SeriesFrame:
        return replace(self, df=df, name=name or self.name)

    def same_calendar(self, *others: SeriesFrame) -> None:
        for o in others:
            if o.calendar != self.calendar:
                raise ValueError(f"series on different calendars: {self.calendar.id} and {o.calendar.id}")

    # ---- entries ------------------------------------------------------------------------------------------------------

    def slice(self, start: int, end: int) -> SeriesFrame:
        """Entries from ``start`` to ``end``, both included; the filter reaches the scan."""
        return self.with_df(self.df.where(F.col("idx").between(start, end)))

    def at(self, idx: int) -> SeriesFrame:
        return self.slice(idx, idx)

    def between(self, t0: Column, t1: Column) -> SeriesFrame:
        return self.with_df(self.df.where(F.col("idx").between(self.calendar.index_of(t0), self.calendar.index_of(t1))))

    def timed(self) -> DataFrame:
        return self.df.withColumn("t", self.calendar.instant(F.col("idx")))

    def sparsify(self) -> SeriesFrame:
        return self.with_df(self.df.where(F.col("v").isNotNull()))

    def densify(self, n: int | None = None) -> SeriesFrame:
        """A row for every calendar entry of every series; empty ones are NULL."""
        size = n or self.calendar.n
        ids = self.df.select("series_id").distinct()
        grid = ids.select("series_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(size - 1).cast("long"))).alias("idx"))
        return self.with_df(grid.join(self.df, ["series_id", "idx"], "left"))

    def states(self) -> DataFrame:
        return self.df.withColumn("state", nulls.state(F.col("v")))

    def null_report(self) -> DataFrame:
        s = nulls.state(F.col("v"))
        return self.df.groupBy("series_id").agg(*[F.count_if(s == k).alias(f"n_{k}") for k in ("value", "empty", "unknown")])

    def fill(self, how: str = "previous", value: float | None = None) -> SeriesFrame:
        """Fill empty entries of a dense frame: with a value, the previous or next one, or on the line between them."""
        v, w = F.col("v"), Window.partitionBy("series_id").orderBy("idx")
        back, ahead = w.rowsBetween(Window.unboundedPreceding, 0), w.rowsBetween(0, Window.unboundedFollowing)
        prev, nxt = F.last(v, ignorenulls=True).over(back), F.first(v, ignorenulls=True).over(ahead)
        if how == "value":
            new = F.coalesce(v, F.lit(value))
        elif how == "previous":
            new = prev
        elif how == "next":
            new = nxt
        elif how == "linear":
            at = F.when(v.isNotNull(), F.col("idx"))
            i0, i1 = F.last(at, ignorenulls=True).over(back), F.first(at, ignorenulls=True).over(ahead)
            new = F.coalesce(v, prev + (nxt - prev) * (F.col("idx") - i0) / F.nullif(i1 - i0, F.lit(0)))
        elif how == "drop":
            return self.sparsify()
        else:
            raise ValueError(f"unknown fill: {how}")
        return self.with_df(self.df.withColumn("v", new))

    def describe(self) -> DataFrame:
        """Name, calendar, number of entries, first and last index of each series."""
        return self.df.groupBy("series_id").agg(F.count("v").alias("entries"), F.min("idx").alias("first_idx"), F.max("idx").alias("last_idx")).withColumn("calendar", F.lit(self.calendar.id))

    # ---- calendar units -----------------------------------------------------------------------------------------------

    def reduce(self, unit: str, agg: str = "avg") -> SeriesFrame:
        """To a coarser calendar with an aggregate of each unit."""
        to = self.calendar.coarser(unit)
        rows = self.timed().select("series_id", to.index_of(F.col("t")).alias("idx"), "v", F.col("idx").alias("_o"))
        return SeriesFrame(rows.groupBy("series_id", "idx").agg(AGGREGATES[agg](F.col("v"), F.col("_o")).alias("v")), to, self.name)

    def expand(self, unit: str, fill: str = "step") -> SeriesFrame:
        """To a finer calendar: each entry repeated, on the line to the next, or followed by empty or unknown ones."""
        from .calendar import SECONDS

        ratio = SECONDS[self.calendar.unit] // SECONDS[unit]
        to = Calendar(self.calendar.origin, unit, self.calendar.n * ratio if self.calendar.n else None)
        base = self.df
        if fill == "linear":
            w = Window.partitionBy("series_id").orderBy("idx")
            base = base.withColumn("_next", F.lead("v").over(w)).withColumn("_gap", F.lead("idx").over(w) - F.col("idx"))
        rows = base.withColumn("_k", F.explode(F.sequence(F.lit(0), F.lit(ratio - 1))))
        v = F.col("v")
        if fill == "linear":
            v = F.when(F.col("_next").isNull(), F.when(F.col("_k") == 0, v)).otherwise(v + (F.col("_next") - v) * F.col("_k") / (F.col("_gap") * ratio))
        elif fill in ("empty", "unknown"):
            v = F.when(F.col("_k") == 0, v).otherwise(nulls.empty() if fill == "empty" else nulls.unknown())
        elif fill != "step":
            raise ValueError(f"unknown fill: {fill}")
        return SeriesFrame(rows.select("series_id", (F.col("idx") * ratio + F.col("_k")).alias("idx"), v.alias("v")).where("v IS NOT NULL"), to, self.name)

    # ---- arithmetic as operators --------------------------------------------------------------------------------------

    def __add__(self, other: SeriesFrame) -> SeriesFrame:
        from .operators import algebra

        return algebra.plus(self, other)

    def __sub__(self, other: SeriesFrame) -> SeriesFrame:
        from .operators import algebra

        return algebra.minus(self, other)

    def __mul__(self, other: SeriesFrame | float) -> SeriesFrame:
        from .operators import algebra

        return algebra.mult(self, other) if isinstance(other, SeriesFrame) else algebra.scale(self, other)

    __rmul__ = __mul__

    def __truediv__(self, other: SeriesFrame) -> SeriesFrame:
        from .operators import algebra

        return algebra.ratio(self, other)

    def __neg__(self) -> SeriesFrame:
        from .operators import algebra

        return algebra.scale(self, -1.0)


def snap(v: Column, digits: int) -> Column:
    """Round for comparison with another engine: a small offset moves exact ties, which engines round to either side,
    off the edge."""
    return F.round(v + F.lit(OFFSET / 10**digits), digits)


#: Fixed value: the offset, in units of the last digit kept.
OFFSET = 0.031415927


def result(sf: SeriesFrame | DataFrame, digits: int = 4) -> DataFrame:
    """The form in which queries return a series: rounded values, states spelled out."""
    df = sf.df if isinstance(sf, SeriesFrame) else sf
    v = F.when(~nulls.is_unknown(F.col("v")), snap(F.col("v"), digits))
    return df.select("series_id", "idx", v.alias("v"), nulls.state(F.col("v")).alias("state"))
