"""Sliding windows and the indicators built on them.

Frames are ranges of ``idx``, so that a window reaches so many calendar entries back whether or not each has a row.
An unknown value in the frame makes the result unknown; empty ones are skipped. Frames that contain a column ``seg``
are evaluated segment by segment."""

from __future__ import annotations

import functools
import inspect
import math
from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame, Window, WindowSpec
from pyspark.sql import functions as F

from .. import nulls
from ..series import SeriesFrame


def keys(a: SeriesFrame) -> list[str]:
    return ["series_id", "seg"] if "seg" in a.df.columns else ["series_id"]


def spec(a: SeriesFrame) -> WindowSpec:
    return Window.partitionBy(*keys(a)).orderBy("idx")


def bounds(w: int, frame: str) -> tuple[int, int]:
    if frame == "trailing":
        return -(w - 1), 0
    if frame == "lagged":
        return -w, -1
    if frame == "steps":  # the w steps that end at t
        return -w, 0
    raise ValueError(f"unknown frame: {frame}")


def over(a: SeriesFrame, w: int, frame: str = "trailing") -> WindowSpec:
    return spec(a).rangeBetween(*bounds(w, frame))


def real(v: Column) -> Column:
    return F.when(~nulls.is_unknown(v), v)


def agg_over(v: Column, fn: Callable[[Column], Column], w: WindowSpec) -> Column:
    """An aggregate of the real values of a frame, unknown if one of them is."""
    return F.when(F.max(nulls.is_unknown(v)).over(w), nulls.unknown()).otherwise(fn(real(v)).over(w))


def put(a: SeriesFrame, v: Column) -> SeriesFrame:
    """Replace the values; entries without a result are dropped."""
    return a.with_df(a.df.withColumn("v", v).where("v IS NOT NULL"))


# ---- the border ---------------------------------------------------------------------------------------------------------


def with_first(a: SeriesFrame, op: Callable[[SeriesFrame], SeriesFrame], k: int) -> SeriesFrame:
    """``op`` on series that have their first value at the ``k`` entries before their start too."""
    rows = a.df.select("series_id", "idx", "v", F.lit(False).alias("_pad"))
    start = rows.where("v IS NOT NULL").groupBy("series_id").agg(F.min("idx").alias("_i0"), F.min_by("v", "idx").alias("v"))
    if not k:
        return op(a)
    pads = start.select("series_id", F.explode(F.sequence(F.col("_i0") - k, F.col("_i0") - 1)).alias("idx"), "v", F.lit(True).alias("_pad"))
    out = op(a.with_df(rows.unionAll(pads)))
    if "_pad" in out.df.columns:
        return out.with_df(out.df.where(~F.col("_pad")).drop("_pad"))
    own = out.df.join(start.select("series_id", "_i0"), "series_id").where(F.col("idx") >= F.col("_i0"))
    return out.with_df(own.drop("_i0"))


def bordered(reach: Callable[..., int]) -> Callable:
    """Gives an operator the argument ``border``: "partial" uses the entries there are, "first" repeats the first value
    before the start. ``reach`` tells from the operator's arguments how many entries that takes."""

    def wrap(f):
        @functools.wraps(f)
        def g(a: SeriesFrame, *args, border: str = "partial", **kw):
            if border == "partial":
                return f(a, *args, **kw)
            if border != "first":
                raise ValueError(f"unknown border: {border}")
            given = inspect.signature(f).bind(a, *args, **kw)
            given.apply_defaults()
            return with_first(a, lambda x: f(x, *args, **kw), reach(given.arguments))

        return g

    return wrap


def by_segments(a: SeriesFrame, op: Callable[[SeriesFrame], SeriesFrame], left: int, length: int = 4096) -> SeriesFrame:
    """``op`` inside segments, so that running sums start anew in each; frames that are cut already stay as they are."""
    from ..plans.segments import eval_segmented

    return op(a) if "seg" in a.df.columns else eval_segmented(a, op, left, 0, max(length, left))


def running(x: Column, upto: WindowSpec, gone: WindowSpec) -> Column:
    """What a frame adds up to: the difference of two running sums."""
    return F.coalesce(F.sum(x).over(upto), F.lit(0)) - F.coalesce(F.sum(x).over(gone), F.lit(0))


#: Unknown entries are counted in the upper half of a long, the others in the lower, so that one sum counts both.
UNKNOWNS = 1 << 32


def counter(v: Column) -> Column:
    return F.when(nulls.is_unknown(v), F.lit(UNKNOWNS)).when(v.isNotNull(), F.lit(1))


@bordered(lambda p: p["w"] - (p["frame"] == "trailing"))
def win(a: SeriesFrame, fn: Callable[[Column], Column], w: int, frame: str = "lagged") -> SeriesFrame:
    """Any Spark aggregate of the ``w`` entries before t (``lagged``), or up to t (``trailing``)."""
    return put(a, agg_over(F.col("v"), fn, over(a, w, frame)))


def win_list(a: SeriesFrame, fn: Callable[[Column], Column], w: int, frame: str = "lagged") -> SeriesFrame:
    """A function of the array of a frame's values, oldest first."""
    s = over(a, w, frame)
    v = F.col("v")
    return put(a, F.when(F.max(nulls.is_unknown(v)).over(s), nulls.unknown()).otherwise(fn(F.collect_list("v").over(s))))


def win_python(a: SeriesFrame, fn: Callable[[list], float], w: int, frame: str = "trailing") -> SeriesFrame:
    """Any Python function of a frame's values, called once per entry: the generic and slow way."""
    lo, hi = bounds(w, frame)
    cols = a.df.columns

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("idx").reset_index(drop=True)
        idx, v = pdf["idx"].to_numpy(), pdf["v"].to_numpy()
        left, right = idx.searchsorted(idx + lo, "left"), idx.searchsorted(idx + hi, "right")
        pdf["v"] = [fn(list(v[x:y])) if y > x else None for x, y in zip(left, right, strict=True)]
        return pdf[cols]

    return a.with_df(a.df.groupBy(*keys(a)).applyInPandas(one, a.df.schema).where("v IS NOT NULL"))


def tumbling(a: SeriesFrame, w: int, fn: Callable[[Column], Column] = F.avg, only_complete: bool = False) -> SeriesFrame:
    """One entry, the last of each, for consecutive windows of ``w`` entries."""
    g = F.floor(F.col("idx") / w).alias("_g")
    rows = a.df.groupBy("series_id", g).agg(fn(F.col("v")).alias("v"), F.count("v").alias("_n"))
    rows = rows.where(F.col("_n") == w) if only_complete else rows
    return a.with_df(rows.select("series_id", (F.col("_g") * w + w - 1).alias("idx"), "v"))


def stepped(a: SeriesFrame, w: int, step: int, fn: Callable[[Column], Column] = F.avg, only_complete: bool = False) -> SeriesFrame:
    """Windows of ``w`` entries that begin every ``step``; the entry of a window is its last one."""
    first = F.greatest(F.lit(0).cast("long"), F.ceil((F.col("idx") - (w - 1)) / step))
    last = F.floor(F.col("idx") / step)
    rows = a.df.where(first <= last).withColumn("_k", F.explode(F.sequence(first, last)))
    rows = rows.groupBy("series_id", "_k").agg(fn(F.col("v")).alias("v"), F.count("v").alias("_n"))
    rows = rows.where(F.col("_n") == w) if only_complete else rows
    return a.with_df(rows.select("series_id", (F.col("_k") * step + w - 1).alias("idx"), "v"))


def predicate_windows(a: SeriesFrame, start: Callable[[Column], Column], end: Callable[[Column], Column] | None = None, only_ended: bool = False) -> DataFrame:
    """Windows that begin wherever ``start`` holds: their first and last entry, size and mean. With ``end`` a window goes
    on, whatever starts inside, to the first entry where that holds, and what follows waits for the next start;
    ``only_ended`` leaves out a window that the series ends in."""
    v = F.col("v")
    if end is None:
        begun = F.sum(F.when(start(v), 1).otherwise(0)).over(spec(a).rowsBetween(Window.unboundedPreceding, 0))
        rows = a.df.withColumn("win", begun).where("win > 0")
    else:
        # the ends cut the series; in each piece the first start opens the window
        before = spec(a).rowsBetween(Window.unboundedPreceding, -1)
        rows = a.df.withColumn("_ends", F.coalesce(end(v), F.lit(False))).withColumn("_piece", F.coalesce(F.sum(F.col("_ends").cast("int")).over(before), F.lit(0)))
        piece = Window.partitionBy(*keys(a), "_piece")
        rows = rows.withColumn("_from", F.min(F.when(start(v), F.col("idx"))).over(piece)).withColumn("_whole", F.max("_ends").over(piece))
        rows = rows.where(F.col("idx") >= F.col("_from"))
        rows = rows.where("_whole") if only_ended else rows
        opened = (F.col("idx") == F.col("_from")).cast("int")
        rows = rows.withColumn("win", F.sum(opened).over(spec(a).rowsBetween(Window.unboundedPreceding, 0)))
    return rows.groupBy("series_id", "win").agg(F.min("idx").alias("first_idx"), F.max("idx").alias("last_idx"), F.count("v").alias("n"), F.avg("v").alias("mean"))


# ---- moving averages --------------------------------------------------------------------------------------------------


def mavg(a: SeriesFrame, w: int, method: str = "sliding", border: str = "partial", frame: str = "trailing") -> SeriesFrame:
    """Moving average, by method: ``sliding`` sums each frame, ``prefix`` takes the difference of two running sums, which
    start anew in every segment (its cost doesn't grow with w), ``packed`` works on arrays, ``pandas`` calls Python,
    ``selfjoin`` joins positions.

    ``border``: before the w-th entry use the entries there are, repeat the first one, or give no result."""
    if border == "first":
        return with_first(a, lambda x: mavg(x, w, method, "partial", frame), w - (frame == "trailing"))
    if border == "strict":
        at0 = a.df.where("v IS NOT NULL").groupBy("series_id").agg(F.min("idx").alias("_i0"))
        out = mavg(a, w, method, "partial", frame)
        return out.with_df(out.df.join(at0, "series_id").where(F.col("idx") >= F.col("_i0") + (w - 1)).drop("_i0"))
    v = F.col("v")
    if method == "sliding":
        s = over(a, w, frame)
        total, n = F.sum(real(v)).over(s), F.count(real(v)).over(s)
        return put(a, F.when(F.max(nulls.is_unknown(v)).over(s), nulls.unknown()).when(n > 0, total / n))
    if method == "prefix":
        lo, hi = bounds(w, frame)

        def differences(x: SeriesFrame) -> SeriesFrame:
            upto, gone = spec(x).rangeBetween(Window.unboundedPreceding, hi), spec(x).rangeBetween(Window.unboundedPreceding, lo - 1)
            n = running(counter(v), upto, gone)
            return put(x, F.when(n >= UNKNOWNS, nulls.unknown()).when(n > 0, running(real(v), upto, gone) / n))

        return by_segments(a, differences, -lo)
    if method == "packed":
        from ..plans.segments import packed_mavg

        return packed_mavg(a, w)
    if method == "pandas":
        return win_python(a, lambda x: sum(x) / len(x), w, frame)
    if method == "selfjoin":
        return selfjoin_avg(a, w)
    raise ValueError(f"unknown method: {method}")


def selfjoin_avg(a: SeriesFrame, w: int) -> SeriesFrame:
    """The naive way: every entry meets those of its frame in a join on cells of w entries."""
    x = a.df.select("series_id", "idx", F.floor(F.col("idx") / w).alias("c"))
    y = a.df.select("series_id", F.col("idx").alias("j"), "v", F.explode(F.array(F.floor(F.col("idx") / w), F.floor(F.col("idx") / w) + 1)).alias("c"))
    hit = x.join(y, ["series_id", "c"]).where(F.col("j").between(F.col("idx") - (w - 1), F.col("idx")))
    return a.with_df(hit.groupBy("series_id", "idx").agg(F.avg("v").alias("v")))


def selfjoin_rsi(a: SeriesFrame, w: int) -> SeriesFrame:
    """Relative strength with every entry meeting every earlier one of its series, and the window tested last: the
    quadratic baseline, whose cost doesn't depend on w."""
    x, y = a.df.alias("x"), a.df.alias("y")
    steps = x.join(y, (F.col("x.series_id") == F.col("y.series_id")) & (F.col("y.idx") <= F.col("x.idx")))
    d = steps.groupBy(F.col("x.series_id").alias("series_id"), F.col("x.idx").alias("idx")).agg(
        (F.max(F.col("x.v")) - F.max(F.when(F.col("y.idx") == F.col("x.idx") - 1, F.col("y.v")))).alias("d"))
    l, r = d.alias("l"), d.alias("r")
    pairs = l.join(r, (F.col("l.series_id") == F.col("r.series_id")) & (F.col("r.idx") <= F.col("l.idx")))
    here = F.when(F.col("r.idx") > F.col("l.idx") - w, F.col("r.d"))
    g, n = F.sum(F.greatest(here, F.lit(0.0))), F.count(here)
    both = g + F.sum(F.greatest(-here, F.lit(0.0)))
    rows = pairs.groupBy(F.col("l.series_id").alias("series_id"), F.col("l.idx").alias("idx")).agg(F.when(n > 0, nulls.divide(g * 100, both)).alias("v"))
    return a.with_df(rows.where("v IS NOT NULL"))


@bordered(lambda p: p["w"] - 1)
def wavg(a: SeriesFrame, w: int) -> SeriesFrame:
    """Average with weights w, w - 1, ... from the newest entry back, from two sums of each frame."""
    return put(a, wavg_column(a, w))


def wavg_column(a: SeriesFrame, w: int) -> Column:
    s = over(a, w)
    v = F.col("v")
    x, i = real(v), F.when(real(v).isNotNull(), F.col("idx"))
    shift_ = F.lit(w) - F.col("idx")
    top = shift_ * F.sum(x).over(s) + F.sum(x * i).over(s)
    return F.when(F.max(nulls.is_unknown(v)).over(s), nulls.unknown()).otherwise(top / (shift_ * F.count(x).over(s) + F.sum(i).over(s)))


def span(alpha: float) -> int:
    """Entries over which the weights (1 - alpha)^-age stay numbers."""
    return 10**9 if alpha <= 0 else 1 if alpha >= 1 else int(690 / -math.log(1.0 - alpha))


@bordered(lambda p: p["w"] - 1)
def xavg(a: SeriesFrame, w: int, alpha: float | None = None, normalize: bool = True, method: str = "auto") -> SeriesFrame:
    """Exponential average of w entries: weights (1 - alpha)^age.

    ``fold`` adds up each frame; ``prefix`` takes the difference of two running sums of values that grow by age, so its
    cost doesn't grow with w; it needs segments short enough for (1 - alpha)^-length to stay a number. ``auto`` cuts
    whole series into such segments, and inside given ones takes the form that is safe there."""
    fits = span(2.0 / (w + 1) if alpha is None else alpha) - w
    if method == "auto" and "seg" not in a.df.columns and fits >= w:
        return by_segments(a, lambda x: put(x, xavg_column(x, w, alpha, normalize, "prefix")), w - 1, min(4096, fits))
    return put(a, xavg_column(a, w, alpha, normalize, method))


def xavg_column(a: SeriesFrame, w: int, alpha: float | None = None, normalize: bool = True, method: str = "auto") -> Column:
    alpha = 2.0 / (w + 1) if alpha is None else alpha
    q = 1.0 - alpha
    v = F.col("v")
    if method == "auto":
        method = "prefix" if a.seg_length is not None and a.seg_length <= span(alpha) else "fold"
    if method == "fold":
        s = over(a, w)
        items = F.collect_list(F.struct(F.col("idx").alias("i"), real(v).alias("x"))).over(s)
        zero = F.struct(F.lit(0.0).alias("top"), F.lit(0.0).alias("low"))

        def step(acc, item):
            k = F.pow(F.lit(q), (F.col("idx") - item["i"]).cast("double"))
            on = item["x"].isNotNull()
            return F.struct((acc["top"] + F.when(on, k * item["x"]).otherwise(0.0)).alias("top"), (acc["low"] + F.when(on, k).otherwise(0.0)).alias("low"))

        out = F.aggregate(items, zero, step, lambda acc: acc["top"] / F.nullif(acc["low"], F.lit(0.0)) if normalize else acc["top"] * alpha)
        return F.when(F.max(nulls.is_unknown(v)).over(s), nulls.unknown()).otherwise(out)
    if method != "prefix":
        raise ValueError(f"unknown method: {method}")
    base = spec(a)
    upto, gone = base.rangeBetween(Window.unboundedPreceding, 0), base.rangeBetween(Window.unboundedPreceding, -w)
    age = F.col("idx") - (F.col("seg_at") if "seg_at" in a.df.columns else F.lit(0))
    grow = F.pow(F.lit(1.0 / q), age.cast("double"))
    x = real(v)
    top, low = running(x * grow, upto, gone), running(F.when(x.isNotNull(), grow), upto, gone)
    bad = running(F.when(nulls.is_unknown(v), 1), upto, gone) > 0
    return F.when(bad, nulls.unknown()).otherwise(top / F.nullif(low, F.lit(0.0)) if normalize else top / grow * alpha)


# ---- differences, momentum, strength ----------------------------------------------------------------------------------


def back(a: SeriesFrame, k: int) -> Column:
    """The value k entries before, looked up by index; no row, no value."""
    return F.max("v").over(spec(a).rangeBetween(-k, -k))


@bordered(lambda p: p["k"])
def mom(a: SeriesFrame, k: int, kind: str = "diff") -> SeriesFrame:
    fn = {"diff": lambda x, y: x - y, "ratio": lambda x, y: nulls.divide(x, y) * 100, "roc": lambda x, y: (nulls.divide(x, y) - 1) * 100}[kind]
    return put(a, nulls.lift(fn, F.col("v"), back(a, k)))


@bordered(lambda p: p["w"])
def rsi(a: SeriesFrame, w: int = 14, method: str = "sliding") -> SeriesFrame:
    """100 G / (G + L) of the gains and losses of the w steps that end at t; unknown where there was no change."""
    if method == "selfjoin":
        return selfjoin_rsi(a, w)
    if method not in ("sliding", "prefix"):
        raise ValueError(f"unknown method: {method}")

    def whole(x: SeriesFrame) -> SeriesFrame:
        b = x.with_df(x.df.withColumn("_d", F.col("v") - back(x, 1)))
        return x.with_df(put(b, rsi_column(b, w, method)).df.drop("_d"))

    return by_segments(a, whole, w) if method == "prefix" else whole(a)


def rsi_column(b: SeriesFrame, w: int, method: str = "sliding") -> Column:
    """The strength from a frame that has each entry's step in ``_d``."""
    d = F.col("_d")
    known = ~nulls.is_unknown(d)
    up, down = F.when(known, F.greatest(d, F.lit(0.0))), F.when(known, F.greatest(-d, F.lit(0.0)))
    if method == "prefix":
        upto, gone = spec(b).rangeBetween(Window.unboundedPreceding, 0), spec(b).rangeBetween(Window.unboundedPreceding, -w)
        n = running(counter(d), upto, gone)
        g, l = running(up, upto, gone), running(down, upto, gone)
    else:
        s = over(b, w)
        n, g, l = F.sum(counter(d)).over(s), F.sum(up).over(s), F.sum(down).over(s)
    return F.when(n >= UNKNOWNS, nulls.unknown()).when(n > 0, nulls.divide(g * 100, g + l))


@bordered(lambda p: max(p["short"], p["long"]) - 1)
def macd(a: SeriesFrame, short: int = 12, long: int = 26, kind: str = "simple", method: str = "auto") -> SeriesFrame:
    """Short minus long moving average, both from one pass over one ordering."""

    def exponential(x: SeriesFrame, how: str) -> SeriesFrame:
        both = x.with_df(x.df.withColumn("_x", xavg_column(x, short, method=how)).withColumn("_y", xavg_column(x, long, method=how)))
        return x.with_df(put(both, nulls.lift(lambda p, q: p - q, F.col("_x"), F.col("_y"))).df.drop("_x", "_y"))

    if kind == "exp":
        w = max(short, long)
        fits = min(span(2.0 / (short + 1)), span(2.0 / (long + 1))) - w
        if method == "auto" and "seg" not in a.df.columns and fits >= 64:
            return by_segments(a, lambda x: exponential(x, "prefix"), w - 1, min(4096, fits))
        return exponential(a, "fold" if method == "sliding" else method)
    return put(a, macd_column(a, short, long))


def macd_column(a: SeriesFrame, short: int, long: int) -> Column:
    v = F.col("v")
    return nulls.lift(lambda x, y: x - y, agg_over(v, F.avg, over(a, short)), agg_over(v, F.avg, over(a, long)))


def signal(a: SeriesFrame, m: int = 9) -> SeriesFrame:
    return mavg(a, m)


# ---- spread, extremes, slope ------------------------------------------------------------------------------------------


@bordered(lambda p: p["w"] - 1)
def mstd(a: SeriesFrame, w: int, ddof: int = 1) -> SeriesFrame:
    return put(a, agg_over(F.col("v"), F.stddev_samp if ddof else F.stddev_pop, over(a, w)))


@bordered(lambda p: p["w"] - 1)
def mvar(a: SeriesFrame, w: int, ddof: int = 1) -> SeriesFrame:
    return put(a, agg_over(F.col("v"), F.var_samp if ddof else F.var_pop, over(a, w)))


@bordered(lambda p: p["w"] - 1)
def mcount(a: SeriesFrame, w: int) -> SeriesFrame:
    """How many known values the window has; unknown ones make no difference here."""
    return put(a, F.count(real(F.col("v"))).over(over(a, w)).cast("double"))


@bordered(lambda p: p["w"] - 1)
def mfirst(a: SeriesFrame, w: int) -> SeriesFrame:
    return put(a, F.first("v", ignorenulls=True).over(over(a, w)))


@bordered(lambda p: p["w"] - 1)
def mlast(a: SeriesFrame, w: int, frame: str = "lagged") -> SeriesFrame:
    """The last value of the window: of the entries before t unless ``frame`` says otherwise."""
    return put(a, F.last("v", ignorenulls=True).over(over(a, w, frame)))


@bordered(lambda p: p["w"] - 1)
def mmax(a: SeriesFrame, w: int) -> SeriesFrame:
    return put(a, agg_over(F.col("v"), F.max, over(a, w)))


@bordered(lambda p: p["w"] - 1)
def mmin(a: SeriesFrame, w: int) -> SeriesFrame:
    return put(a, agg_over(F.col("v"), F.min, over(a, w)))


def median_of(q: float = 0.5) -> Callable[[Column], Column]:
    return lambda v: F.percentile(v, F.lit(q))


@bordered(lambda p: p["w"] - 1)
def mmedian(a: SeriesFrame, w: int, q: float = 0.5) -> SeriesFrame:
    return put(a, agg_over(F.col("v"), median_of(q), over(a, w)))


@bordered(lambda p: p["w"] - 1)
def mslope(a: SeriesFrame, w: int) -> SeriesFrame:
    """Least-squares slope of the values on the index; needs two entries."""
    return put(a, mslope_column(a, w))


def mslope_column(a: SeriesFrame, w: int) -> Column:
    s, v = over(a, w), F.col("v")
    slope = F.when(F.count(real(v)).over(s) >= 2, F.regr_slope(real(v), F.col("idx").cast("double")).over(s))
    return F.when(F.max(nulls.is_unknown(v)).over(s), nulls.unknown()).otherwise(slope)


def bollinger(a: SeriesFrame, w: int = 20, c: float = 2.0) -> DataFrame:
    s, v = over(a, w), F.col("v")
    mid, dev = agg_over(v, F.avg, s), agg_over(v, F.stddev_pop, s)
    return a.df.select("series_id", "idx", mid.alias("mid"), (mid - c * dev).alias("low"), (mid + c * dev).alias("high"))


@bordered(lambda p: p["w"] - 1)
def zscore(a: SeriesFrame, w: int) -> SeriesFrame:
    return put(a, zscore_column(a, w))


def zscore_column(a: SeriesFrame, w: int) -> Column:
    s, v = over(a, w), F.col("v")
    return nulls.lift(lambda x, m, d: nulls.divide(x - m, d), v, agg_over(v, F.avg, s), agg_over(v, F.stddev_samp, s))


def stochastic(q: SeriesFrame, w: int = 14) -> SeriesFrame:
    """Where the close lies between the lowest low and the highest high; ``q`` has columns low, high and close."""
    s = over(q, w)
    lo, hi = F.min("low").over(s), F.max("high").over(s)
    return q.with_df(q.df.select("series_id", "idx", nulls.lift(lambda c, l, h: nulls.divide((c - l) * 100, h - l), F.col("close"), lo, hi).alias("v")).where("v IS NOT NULL"))


def williams(q: SeriesFrame, w: int = 14) -> SeriesFrame:
    """Where the close lies below the highest high, from 0 down to -100."""
    s = over(q, w)
    lo, hi = F.min("low").over(s), F.max("high").over(s)
    return q.with_df(q.df.select("series_id", "idx", nulls.lift(lambda c, l, h: nulls.divide((h - c) * -100, h - l), F.col("close"), lo, hi).alias("v")).where("v IS NOT NULL"))


def mcov(q: SeriesFrame, x: str, y: str, w: int) -> SeriesFrame:
    s = over(q, w)
    return q.with_df(q.df.select("series_id", "idx", F.when(F.count(F.lit(1)).over(s) >= 2, F.covar_samp(x, y).over(s)).alias("v")).where("v IS NOT NULL"))


def mcorr(q: SeriesFrame, x: str, y: str, w: int) -> SeriesFrame:
    s = over(q, w)
    return q.with_df(q.df.select("series_id", "idx", F.when(F.count(F.lit(1)).over(s) >= 2, F.corr(x, y).over(s)).alias("v")).where("v IS NOT NULL"))


def adx(q: SeriesFrame, w: int = 14, smoothing: str = "simple") -> SeriesFrame:
    """Average directional index of quotes (high, low, close), with simple averages of the last w entries or, as
    ``wilder``, with recursive ones of weight 1 / w from the first entry on."""
    one = spec(q).rangeBetween(-1, -1)
    ph, pl, pc = (F.max(c).over(one) for c in ("high", "low", "close"))
    up, dn = F.col("high") - ph, pl - F.col("low")
    d = q.df.select(
        "series_id", "idx", F.when((up > dn) & (up > 0), up).otherwise(F.lit(0.0)).alias("pdm"), F.when((dn > up) & (dn > 0), dn).otherwise(F.lit(0.0)).alias("mdm"),
        F.greatest(F.col("high") - F.col("low"), F.abs(F.col("high") - pc), F.abs(F.col("low") - pc)).alias("tr"), pc.alias("pc"),
    ).where("pc IS NOT NULL")
    if smoothing == "wilder":
        from ..plans.segments import xavg_recursive
        from .algebra import wide

        smooth = lambda c: xavg_recursive(q.with_df(d.select("series_id", "idx", F.col(c).alias("v"))), 1.0 / w)
        rows = wide([smooth(c) for c in ("pdm", "mdm", "tr")])
        p, m = (nulls.lift(lambda x, t: nulls.divide(x * 100, t), F.col(c), F.col("v2")) for c in ("v0", "v1"))
        dx = rows.select("series_id", "idx", nulls.lift(lambda x, y: nulls.divide(F.abs(x - y) * 100, x + y), p, m).alias("v"))
        return xavg_recursive(q.with_df(dx.where("NOT isnan(v)")), 1.0 / w)
    if smoothing != "simple":
        raise ValueError(f"unknown smoothing: {smoothing}")
    b = q.with_df(d)
    s = over(b, w)
    tr = F.sum("tr").over(s)
    b = q.with_df(d.select("series_id", "idx", nulls.divide(F.sum("pdm").over(s) * 100, tr).alias("p"), nulls.divide(F.sum("mdm").over(s) * 100, tr).alias("m")))
    dx = b.df.select("series_id", "idx", nulls.lift(lambda p, m: nulls.divide(F.abs(p - m) * 100, p + m), F.col("p"), F.col("m")).alias("v"))
    return mavg(q.with_df(dx), w)


def cross(a: SeriesFrame, b: SeriesFrame, direction: str = "up") -> SeriesFrame:
    """Entries where ``a`` passes ``b``: above it now, not above at the last entry where both are known."""
    from .algebra import wide

    w = wide([a, b], "inner").where(~nulls.is_unknown(F.col("v0")) & ~nulls.is_unknown(F.col("v1")))
    s = Window.partitionBy("series_id").orderBy("idx")
    now, was = F.col("v0") - F.col("v1"), F.lag(F.col("v0") - F.col("v1")).over(s)
    hit = (now > 0) & (was <= 0) if direction == "up" else (now < 0) & (was >= 0)
    return a.with_df(w.withColumn("_h", hit).where("_h").select("series_id", "idx", F.col("v0").alias("v")))


# ---- registry ---------------------------------------------------------------------------------------------------------


class Indicator:
    """A named window operator: how far it looks back, and how a scalar passes through it.

    ``scaling``: "linear" (out by the scalar), "abs", "positive" (only scalars above 0), "free" (no effect above 0), None."""

    def __init__(self, fn: Callable[..., SeriesFrame], lookback: Callable[..., int], scaling: str | None = None):
        self.fn, self.lookback, self.scaling = fn, lookback, scaling


REGISTRY: dict[str, Indicator] = {}


def register_indicator(name: str, fn: Callable[..., SeriesFrame], lookback: Callable[..., int], scaling: str | None = None) -> None:
    REGISTRY[name.upper()] = Indicator(fn, lookback, scaling)


for _name, _fn, _look, _scaling in [
    ("MAVG", mavg, lambda w, **_: w - 1, "linear"), ("XAVG", xavg, lambda w, **_: w - 1, "linear"), ("WAVG", wavg, lambda w, **_: w - 1, "linear"),
    ("MOM", mom, lambda k, **_: k, "linear"), ("RSI", rsi, lambda w=14, **_: w, "free"), ("MSTD", mstd, lambda w, **_: w - 1, "abs"),
    ("MMAX", mmax, lambda w, **_: w - 1, "positive"), ("MMIN", mmin, lambda w, **_: w - 1, "positive"), ("MSLOPE", mslope, lambda w, **_: w - 1, "linear"),
    ("MACD", macd, lambda short=12, long=26, **_: max(short, long) - 1, "linear"), ("ZSCORE", zscore, lambda w, **_: w - 1, "free"), ("MMEDIAN", mmedian, lambda w, **_: w - 1, "positive"),
    ("MVAR", mvar, lambda w, **_: w - 1, None), ("MCOUNT", mcount, lambda w, **_: w - 1, None), ("MFIRST", mfirst, lambda w, **_: w - 1, "linear"), ("MLAST", mlast, lambda w, **_: w, "linear"),
]:
    register_indicator(_name, _fn, _look, _scaling)


def indicator(name: str, a: SeriesFrame, **params) -> SeriesFrame:
    return REGISTRY[name.upper()].fn(a, **params)
