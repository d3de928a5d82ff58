"""Cutting long series into equal segments with overlaps, so that windows are evaluated segment by segment."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..series import SeriesFrame


def segment(a: SeriesFrame, length: int = 1024, left: int = 128, right: int = 128) -> SeriesFrame:
    """Copy each row to every segment whose core or halo it lies in: columns seg, seg_at (its first entry), is_core.

    A halo may be longer than a segment; only segments that have a core row of the series come out."""
    lo = F.floor((F.col("idx") - right) / length)
    hi = F.floor((F.col("idx") + left) / length)
    copies = a.df.withColumn("seg", F.explode(F.sequence(F.greatest(F.lit(0).cast("long"), lo), hi)))
    copies = copies.withColumn("is_core", F.floor(F.col("idx") / length) == F.col("seg"))
    return replace(a.with_df(copies.withColumn("seg_at", F.col("seg") * length)), seg_length=length + left + right)


def core(a: SeriesFrame) -> SeriesFrame:
    """The rows that belong to their segment, without the segment's columns."""
    return replace(a.with_df(a.df.where("is_core").drop("seg", "seg_at", "is_core")), seg_length=None)


def eval_segmented(a: SeriesFrame, op: Callable[[SeriesFrame], SeriesFrame], lookback: int, lookahead: int = 0, length: int = 1024) -> SeriesFrame:
    """Apply a window operator inside segments whose halo is what the operator reaches."""
    return core(op(segment(a, length, lookback, lookahead)))


def pad_last(a: SeriesFrame, length: int = 1024) -> DataFrame:
    """Segments of core rows with the last one filled up by unknown values; ``padding`` marks those, to be cut again."""
    own = a.df.withColumn("seg", F.floor(F.col("idx") / length)).withColumn("padding", F.lit(False))
    ends = a.df.groupBy("series_id").agg(F.max("idx").alias("e"))
    ends = ends.withColumn("seg", F.floor(F.col("e") / length)).where((F.col("e") + 1) % length != 0)
    extra = ends.select("series_id", F.explode(F.sequence(F.col("e") + 1, (F.col("seg") + 1) * length - 1)).alias("idx"), F.lit(float("nan")).alias("v"), "seg", F.lit(True).alias("padding"))
    return own.select("series_id", "idx", "v", "seg", "padding").unionAll(extra)


def segment_counts(a: SeriesFrame, length: int = 1024, left: int = 128, right: int = 128) -> DataFrame:
    s = segment(a, length, left, right).df
    return s.groupBy("series_id", "seg").agg(F.count(F.lit(1)).alias("n_rows"), F.count_if("is_core").alias("n_core")).where("n_core > 0")


# ---- packed layout ----------------------------------------------------------------------------------------------------


def pack(a: SeriesFrame, length: int = 1024) -> DataFrame:
    """One row per segment: its first entry and the array of its values in order, NULL where empty."""
    rows = a.df.withColumn("seg", F.floor(F.col("idx") / length))
    g = rows.groupBy("series_id", "seg").agg(F.map_from_entries(F.collect_list(F.struct("idx", "v"))).alias("m"), F.min("idx").alias("lo"), F.max("idx").alias("hi"))
    return g.select("series_id", "seg", F.col("lo").alias("start"), F.transform(F.sequence("lo", "hi"), lambda i: F.try_element_at("m", i)).alias("vals"))


def unpack(packed: DataFrame) -> DataFrame:
    rows = packed.select("series_id", "start", F.posexplode("vals").alias("k", "v"))
    return rows.where("v IS NOT NULL").select("series_id", (F.col("start") + F.col("k")).alias("idx"), "v")


def packed_mavg(a: SeriesFrame, w: int, length: int = 1024) -> SeriesFrame:
    """Moving average on arrays: one row per segment with the last w - 1 values before it, running sums inside."""
    seg = segment(a, length, w - 1, 0).df
    g = seg.groupBy("series_id", "seg", "seg_at").agg(F.sort_array(F.collect_list(F.struct("idx", "v"))).alias("xs"))
    start = F.struct(F.lit(0.0).alias("s"), F.array().cast("array<double>").alias("out"))
    run = F.aggregate("xs", start, lambda acc, x: F.struct((acc["s"] + x["v"]).alias("s"), F.concat(acc["out"], F.array(acc["s"] + x["v"])).alias("out")), lambda acc: acc["out"])
    g = g.withColumn("run", run).withColumn("ids", F.transform("xs", lambda x: x["idx"]))
    # dense inside the frame: the position w back is the last index at or before idx - w
    rows = g.select("series_id", "seg_at", "ids", "run", F.posexplode("xs").alias("k", "x"))
    at = F.col("x.idx")
    gone = F.when(F.element_at("ids", F.greatest(F.lit(1), F.col("k") - w + 1)) == at - w, F.col("k") - w + 1).otherwise(F.size(F.filter("ids", lambda i: i <= at - w)))
    s = F.element_at("run", F.col("k") + 1) - F.when(gone > 0, F.element_at("run", F.greatest(F.lit(1), gone))).otherwise(0.0)
    rows = rows.where(at >= F.col("seg_at")).select("series_id", at.alias("idx"), (s / (F.col("k") + 1 - gone)).alias("v"))
    return a.with_df(rows)


# ---- recursive operators: fold per segment, scan over segments, carry back -------------------------------------------


#: Segments whose maps are composed to one before the scan over a series.
GROUP = 256


def xavg_recursive(a: SeriesFrame, alpha: float, length: int = 1024) -> SeriesFrame:
    """y[0] = v[0]; y[t] = alpha v[t] + (1 - alpha) y[t - 1], whatever the length of the series.

    A segment turns the y before it into q^n y + b. Those two numbers per segment are composed by groups of segments,
    scanned over groups, then inside each group; each segment starts anew from its carry. An empty entry keeps y; an
    unknown one makes all after it unknown."""
    from pyspark.sql import Window

    q = 1.0 - alpha
    rows = a.df.where("v IS NOT NULL").withColumn("seg", F.floor(F.col("idx") / length))
    g = rows.groupBy("series_id", "seg").agg(F.sort_array(F.collect_list(F.struct("idx", "v"))).alias("xs"))
    first = rows.groupBy("series_id").agg(F.min_by("v", "idx").alias("v0"))
    part = g.select("series_id", "seg", F.floor(F.col("seg") / GROUP).alias("grp"), F.aggregate("xs", F.lit(0.0), lambda acc, x: acc * q + x["v"] * alpha).alias("b"), F.pow(F.lit(q), F.size("xs").cast("double")).alias("m"))
    one = F.struct(F.lit(1.0).alias("m"), F.lit(0.0).alias("b"))
    maps = F.sort_array(F.collect_list(F.struct("seg", "m", "b")))
    whole = part.groupBy("series_id", "grp").agg(F.aggregate(maps, one, lambda acc, p: F.struct((p["m"] * acc["m"]).alias("m"), (p["m"] * acc["b"] + p["b"]).alias("b"))).alias("all"))
    whole = whole.select("series_id", "grp", "all.m", "all.b")
    before = lambda *key: Window.partitionBy(*key[:-1]).orderBy(key[-1]).rowsBetween(Window.unboundedPreceding, -1)
    go = lambda acc, p: p["m"] * acc + p["b"]
    # the very first value counts whole: y before it is v0
    groups = whole.withColumn("past", F.collect_list(F.struct("m", "b")).over(before("series_id", "grp"))).join(first, "series_id")
    groups = groups.select("series_id", "grp", F.aggregate("past", F.col("v0"), go).alias("y"))
    inside = part.withColumn("past", F.collect_list(F.struct("m", "b")).over(before("series_id", "grp", "seg"))).join(groups, ["series_id", "grp"])
    carry = inside.select("series_id", "seg", F.aggregate("past", F.col("y"), go).alias("y"))
    scan = g.join(carry, ["series_id", "seg"])
    seed = F.struct(F.col("y").alias("y"), F.array().cast("array<double>").alias("out"))
    ys = F.aggregate("xs", seed, lambda acc, x: F.struct((acc["y"] * q + x["v"] * alpha).alias("y"), F.concat(acc["out"], F.array(acc["y"] * q + x["v"] * alpha)).alias("out")), lambda acc: acc["out"])
    out = scan.select("series_id", F.explode(F.arrays_zip("xs", ys.alias("ys"))).alias("p"))
    return a.with_df(out.select("series_id", F.col("p.xs.idx").alias("idx"), F.col("p.ys").alias("v")))
