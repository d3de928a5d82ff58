"""Vector-space and relational-like operators on series of one calendar."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .. import nulls
from ..series import SeriesFrame

KEYS = ["series_id", "idx"]


# ---- joins on time ----------------------------------------------------------------------------------------------------


def wide(frames: list[SeriesFrame], how: str = "full") -> DataFrame:
    """One row per series and entry with columns v0, v1, ...: one grouping of a union, however many series."""
    frames[0].same_calendar(*frames[1:])
    tagged = [f.df.select(*KEYS, F.lit(i).alias("_i"), "v") for i, f in enumerate(frames)]
    every = reduce(DataFrame.unionAll, tagged)
    cols = [F.max(F.when(F.col("_i") == i, F.col("v"))).alias(f"v{i}") for i in range(len(frames))]
    out = every.groupBy(*KEYS).agg(*cols, F.count_distinct("_i").alias("_n")) if how == "inner" else every.groupBy(*KEYS).agg(*cols)
    return out.where(F.col("_n") == len(frames)).drop("_n") if how == "inner" else out


FUNCTIONS: dict[str, Callable[..., Column]] = {
    "SUM": lambda *c: reduce(lambda a, b: a + b, c),
    "AVG": lambda *c: reduce(lambda a, b: a + b, c) / F.lit(len(c)),
    "MIN": lambda *c: F.least(*c), "MAX": lambda *c: F.greatest(*c),
    "PRODUCT": lambda *c: reduce(lambda a, b: a * b, c),
}


def join(frames: list[SeriesFrame], fn: str | Callable[..., Column], strategy: str = "kary") -> SeriesFrame:
    """JOIN of any number of series: ``fn`` of the values of an entry, else the largest null state among them.

    ``strategy``: one k-ary grouping, or a chain of binary joins."""
    f = FUNCTIONS[fn.upper()] if isinstance(fn, str) else fn
    first = frames[0]
    if strategy == "kary":
        rows = wide(frames)
    elif strategy == "binary":
        first.same_calendar(*frames[1:])
        rows = first.df.select(*KEYS, F.col("v").alias("v0"))
        for i, other in enumerate(frames[1:], 1):
            rows = rows.join(other.df.select(*KEYS, F.col("v").alias(f"v{i}")), KEYS, "full")
    else:
        raise ValueError(f"unknown strategy: {strategy}")
    v = nulls.lift(f, *[F.col(f"v{i}") for i in range(len(frames))])
    return first.with_df(rows.select(*KEYS, v.alias("v")).where("v IS NOT NULL"))


def plus(a: SeriesFrame, b: SeriesFrame) -> SeriesFrame:
    return join([a, b], "SUM")


def minus(a: SeriesFrame, b: SeriesFrame) -> SeriesFrame:
    return join([a, b], lambda x, y: x - y)


def mult(a: SeriesFrame, b: SeriesFrame) -> SeriesFrame:
    return join([a, b], "PRODUCT")


def ratio(a: SeriesFrame, b: SeriesFrame) -> SeriesFrame:
    return join([a, b], nulls.divide)


def scale(a: SeriesFrame, s: float) -> SeriesFrame:
    return a.with_df(a.df.withColumn("v", F.col("v") * F.lit(float(s))))


def linear(terms: list[tuple[float, SeriesFrame]]) -> SeriesFrame:
    """The sum of scaled series."""
    return join([s for _, s in terms], lambda *c: reduce(lambda x, y: x + y, [F.lit(float(k)) * v for (k, _), v in zip(terms, c, strict=True)]))


def map_values(a: SeriesFrame, fn: Callable[[Column], Column]) -> SeriesFrame:
    """A mathematical function of the values; where it has none, the result is unknown."""
    v = nulls.lift(lambda x: F.coalesce(fn(x), nulls.unknown()), F.col("v"))
    return a.with_df(a.df.withColumn("v", v))


def shift(a: SeriesFrame, k: int = 1) -> SeriesFrame:
    """The value of entry t - k at t: rows get another index, no window is needed."""
    rows = a.df.withColumn("idx", F.col("idx") + F.lit(k)).where("idx >= 0")
    return a.with_df(rows.where(F.col("idx") < a.calendar.n) if a.calendar.n else rows)


def constant(a: SeriesFrame, c: float) -> SeriesFrame:
    """The constant series with the ids of ``a`` over its whole calendar."""
    d = a.densify()
    return a.with_df(d.df.withColumn("v", F.lit(float(c))))


# ---- products, norms --------------------------------------------------------------------------------------------------


def dot(a: SeriesFrame, b: SeriesFrame) -> DataFrame:
    return wide([a, b], "inner").groupBy("series_id").agg(F.sum(F.col("v0") * F.col("v1")).alias("dot"))


def norm(a: SeriesFrame, p: float = 2.0) -> DataFrame:
    return a.df.groupBy("series_id").agg(F.pow(F.sum(F.pow(F.abs("v"), F.lit(float(p)))), F.lit(1.0 / p)).alias("norm"))


# ---- selection, projection, sets --------------------------------------------------------------------------------------


def select(a: SeriesFrame, pred: Callable[[Column], Column], unknown: str = "keep") -> SeriesFrame:
    """Keep values for which ``pred`` holds; others become empty. An unknown value stays unknown, or becomes empty."""
    v = F.col("v")
    keep = nulls.known(pred(v), v)
    return a.with_df(a.df.where(keep | nulls.is_unknown(v) if unknown == "keep" else keep))


def select_time(a: SeriesFrame, pred: Callable[[Column], Column]) -> SeriesFrame:
    return a.with_df(a.df.where(pred(a.calendar.instant(F.col("idx")))))


def mask(a: SeriesFrame, b: SeriesFrame, pred: Callable[[Column], Column]) -> SeriesFrame:
    """Values of ``a`` where the value of ``b`` at the same entry fulfils ``pred``."""
    a.same_calendar(b)
    m = b.df.where(nulls.known(pred(F.col("v")), F.col("v"))).select(*KEYS)
    return a.with_df(a.df.join(m, KEYS, "left_semi"))


def project(a: SeriesFrame, fn: Callable[[Column], Column], on_empty: float | None = None, on_unknown: float | None = None) -> SeriesFrame:
    """``fn`` of each value; nulls stay what they are unless values are given for them (empties need a dense frame)."""
    v = F.col("v")
    new = F.when(nulls.is_unknown(v), nulls.unknown() if on_unknown is None else F.lit(float(on_unknown)))
    new = new.when(v.isNull(), nulls.empty() if on_empty is None else F.lit(float(on_empty))).otherwise(fn(v))
    return a.with_df(a.df.withColumn("v", new))


def union(a: SeriesFrame, b: SeriesFrame, conflict: str = "left") -> SeriesFrame:
    """Entries of either; where both have a different one, that of the named side, or unknown."""
    w = wide([a, b])
    l, r = F.col("v0"), F.col("v1")
    both = {"left": F.coalesce(l, r), "right": F.coalesce(r, l), "unknown": F.when(l.isNotNull() & r.isNotNull() & (l != r), nulls.unknown()).otherwise(F.coalesce(l, r))}[conflict]
    return a.with_df(w.select(*KEYS, both.alias("v")).where("v IS NOT NULL"))


def intersect(a: SeriesFrame, b: SeriesFrame, match: str = "value", tol: float = 0.0) -> SeriesFrame:
    """Entries of both: with like values, or (``match="time"``) whatever their values, with that of the first."""
    w = wide([a, b], "inner")
    if match == "value":
        w = w.where(F.abs(F.col("v0") - F.col("v1")) <= tol)
    return a.with_df(w.select(*KEYS, F.col("v0").alias("v")))


def minus_entries(a: SeriesFrame, b: SeriesFrame) -> SeriesFrame:
    a.same_calendar(b)
    return a.with_df(a.df.join(b.df.where("v IS NOT NULL").select(*KEYS), KEYS, "left_anti"))


def join_reference(a: SeriesFrame, ref: SeriesFrame, fn: Callable[[Column, Column], Column], most_rows: int = 2_000_000) -> SeriesFrame:
    """Every series of ``a`` with the one series of ``ref`` on the same entries. A reference of at most ``most_rows``
    calendar entries is broadcast, as that bounds its size; a longer or endless one is joined by shuffle."""
    a.same_calendar(ref)
    r = ref.df.select("idx", F.col("v").alias("_r"))
    if a.calendar.n and a.calendar.n <= most_rows:
        r = F.broadcast(r)
    return a.with_df(a.df.join(r, "idx").select(*KEYS, nulls.lift(fn, F.col("v"), F.col("_r")).alias("v")))


def join_values(a: SeriesFrame, b: SeriesFrame, width: float) -> DataFrame:
    """Pairs of entries whose values lie within ``width``: equal or neighbouring cells of that width, then the test."""
    cell = F.floor(F.col("v") / F.lit(width)).cast("long")
    x = a.df.where(~nulls.is_unknown(F.col("v")) & F.col("v").isNotNull()).select(F.col("series_id").alias("a_id"), F.col("idx").alias("a_idx"), F.col("v").alias("a_v"), cell.alias("c"))
    y = b.df.where(~nulls.is_unknown(F.col("v")) & F.col("v").isNotNull()).select(F.col("series_id").alias("b_id"), F.col("idx").alias("b_idx"), F.col("v").alias("b_v"), F.explode(F.array(cell - 1, cell, cell + 1)).alias("c"))
    return x.join(y, "c").where(F.abs(F.col("a_v") - F.col("b_v")) <= width).drop("c")
