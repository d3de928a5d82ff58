"""Joins that Spark has no operator for: as-of, point in interval, and overlap of intervals."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, by: list[str], on: str, value: list[str], tolerance: float | None = None, direction: str = "backward", tie: list[str] | None = None) -> DataFrame:
    """For each left row the values of the latest right row at or before it (``backward``), the earliest at or after it
    (``forward``) or the closer of both (``nearest``, ties go back); columns of the right get the prefix r_.

    One shuffle on ``by``: a tagged union in which each row looks along the order for the last right row."""
    tie = tie or []
    names = [c for c in left.columns if c not in (*by, on)]
    right_cols = [*value, *[t for t in tie if t not in value]]
    l = left.select(*by, on, *names, *[F.lit(None).cast(right.schema[c].dataType).alias(f"r_{c}") for c in right_cols], F.lit(None).cast(left.schema[on].dataType).alias(f"r_{on}"), F.lit(1).alias("_side"))
    r = right.select(*by, on, *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in names], *[F.col(c).alias(f"r_{c}") for c in right_cols], F.col(on).alias(f"r_{on}"), F.lit(0).alias("_side"))
    both = l.unionByName(r)
    hit = F.when(F.col("_side") == 0, F.struct(*[f"r_{c}" for c in (on, *right_cols)]))
    keys = [F.col(f"r_{t}").asc_nulls_last() for t in tie]
    up = Window.partitionBy(*by).orderBy(F.col(on), F.col("_side"), *keys)
    down = Window.partitionBy(*by).orderBy(F.col(on).desc(), F.col("_side"), *[F.col(f"r_{t}").desc() for t in tie])
    back = F.last(hit, ignorenulls=True).over(up.rowsBetween(Window.unboundedPreceding, 0))
    ahead = F.last(hit, ignorenulls=True).over(down.rowsBetween(Window.unboundedPreceding, 0))
    gap = lambda h: F.abs(F.unix_micros(F.col(on).cast("timestamp")) - F.unix_micros(h[f"r_{on}"].cast("timestamp"))) / 1e6 if "timestamp" in left.schema[on].dataType.simpleString() else F.abs(F.col(on) - h[f"r_{on}"])
    if direction == "nearest":
        found = both.withColumn("_b", back).withColumn("_f", ahead)
        hit_col = F.when(F.col("_f").isNull() | (gap(F.col("_b")) <= gap(F.col("_f"))), F.col("_b")).otherwise(F.col("_f"))
        found = found.withColumn("_h", hit_col)
    else:
        found = both.withColumn("_h", back if direction == "backward" else ahead)
    ok = F.lit(True) if tolerance is None else gap(F.col("_h")) <= tolerance
    out = found.where("_side = 1").withColumn("_h", F.when(ok, F.col("_h")))
    return out.select(*by, on, *names, *[F.col(f"_h.r_{c}").alias(f"r_{c}") for c in (on, *value)])


def range_join(points: DataFrame, intervals: DataFrame, at: str, start: str, end: str, width: int, by: list[str] | None = None) -> DataFrame:
    """Points with the intervals [start, end) they lie in. Intervals are cut into cells of ``width``; a cell meets its
    points in an equi-join, and the exact test follows."""
    by = by or []
    cell = lambda c: F.floor(c / F.lit(width)).cast("long")
    i = intervals.where(F.col(start) < F.col(end)).withColumn("_c", F.explode(F.sequence(cell(F.col(start)), cell(F.col(end) - 1))))
    return points.withColumn("_c", cell(F.col(at))).join(i, [*by, "_c"]).where((F.col(at) >= F.col(start)) & (F.col(at) < F.col(end))).drop("_c")


def overlap_join(left: DataFrame, right: DataFrame, width: int, l_start: str = "l_start", l_end: str = "l_end", r_start: str = "r_start", r_end: str = "r_end") -> DataFrame:
    """Pairs of intervals (both ends included) that share a point; each pair comes out of the first cell they share."""
    cell = lambda c: F.floor(c / F.lit(width)).cast("long")
    a = left.withColumn("_c", F.explode(F.sequence(cell(F.col(l_start)), cell(F.col(l_end)))))
    b = right.withColumn("_c", F.explode(F.sequence(cell(F.col(r_start)), cell(F.col(r_end)))))
    first = F.greatest(cell(F.col(l_start)), cell(F.col(r_start)))
    meet = (F.col(l_start) <= F.col(r_end)) & (F.col(r_start) <= F.col(l_end)) & (F.col("_c") == first)
    return a.join(b, "_c").where(meet).drop("_c")


def salted_join(left: DataFrame, right: DataFrame, on: str, salts: int = 16, how: str = "inner") -> DataFrame:
    """An equi-join for a left side with hot keys: its rows spread over ``salts`` copies of each right row."""
    if how not in ("inner", "left", "left_semi", "left_anti"):
        raise ValueError("only the right side may be copied")
    cols: list[Column] = [F.col(c) for c in left.columns]
    l = left.withColumn("_s", F.pmod(F.xxhash64(*cols), F.lit(salts)))
    r = right.withColumn("_s", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return l.join(r, [on, "_s"], how).drop("_s")
