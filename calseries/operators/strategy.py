"""Trading strategies: buy and sell series, their simulation on the past, and grids of parameters."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import nulls
from ..calendar import unit_window
from ..series import SeriesFrame
from . import algebra, window


def buy_macd(a: SeriesFrame, short: int = 12, long: int = 26, smooth: int = 9) -> SeriesFrame:
    """Entries where the smoothed difference of the short and the long average is positive."""
    line = window.mavg(window.macd(a, short, long), smooth)
    return algebra.select(line, lambda v: v > 0)


def sell_ratio(a: SeriesFrame, long: int = 26, short: int = 12, factor: float = 1.1) -> SeriesFrame:
    """Entries where the long average exceeds the short one by a factor; both averages are one pass over one ordering."""
    v = F.col("v")
    x, y = window.agg_over(v, F.avg, window.over(a, long)), window.agg_over(v, F.avg, window.over(a, short))
    return algebra.select(window.put(a, nulls.lift(nulls.divide, x, y)), lambda r: r > factor)


@dataclass(frozen=True)
class Strategy:
    """A buy and a sell query with their parameters."""

    short: int = 12
    long: int = 26
    smooth: int = 9
    factor: float = 1.1

    def scaled(self, unit: str, hours_per_day: float = 8.5) -> Strategy:
        """The same strategy, its windows given in days, on entries of another unit."""
        n = lambda days: unit_window(days, unit, hours_per_day)
        return Strategy(n(self.short), n(self.long), n(self.smooth), self.factor)

    def events(self, price: SeriesFrame) -> DataFrame:
        """(series_id, idx, v, event) for every entry of the price: 1 buys, 0 sells, none otherwise; a sale wins."""
        buy = buy_macd(price, self.short, self.long, self.smooth).df.where(~nulls.is_unknown(F.col("v"))).select("series_id", "idx", F.lit(True).alias("_buy"))
        sell = sell_ratio(price, self.long, self.short, self.factor).df.where(~nulls.is_unknown(F.col("v"))).select("series_id", "idx", F.lit(True).alias("_sell"))
        rows = price.df.join(buy, ["series_id", "idx"], "left").join(sell, ["series_id", "idx"], "left")
        event = F.when(F.col("_sell"), 0).when(F.col("_buy"), 1)
        return rows.select("series_id", "idx", "v", event.alias("event"))


def positions(events: DataFrame, by: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """The position after each entry: that of the last event at or before it, flat before any."""
    w = Window.partitionBy(*by).orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
    return events.withColumn("position", F.coalesce(F.last("event", ignorenulls=True).over(w), F.lit(0)))


def summarize(pos: DataFrame, by: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """Trades, hit rate, return and largest drawdown of each group; an open trade closes at the last price."""
    w = Window.partitionBy(*by).orderBy("idx")
    steps = pos.withColumn("was", F.coalesce(F.lag("position").over(w), F.lit(0))).withColumn("growth", F.when(F.col("was") == 1, F.ln(F.col("v") / F.lag("v").over(w))).otherwise(F.lit(0.0)))
    run = w.rowsBetween(Window.unboundedPreceding, 0)
    steps = steps.withColumn("opened", (F.col("position") == 1) & (F.col("was") == 0)).withColumn("trade", F.sum(F.when(F.col("opened"), 1).otherwise(0)).over(run))
    steps = steps.withColumn("level", F.sum("growth").over(run))
    steps = steps.withColumn("down", 1 - F.exp(F.col("level") - F.greatest(F.lit(0.0), F.max("level").over(run))))
    # the step that leaves the market still belongs to the trade: its growth counts while ``was`` is 1
    trades = steps.where("trade > 0").groupBy(*by, "trade").agg(F.sum("growth").alias("g"))
    per = trades.groupBy(*by).agg(F.count(F.lit(1)).alias("trades"), F.count_if(F.col("g") > 0).alias("wins"))
    total = steps.groupBy(*by).agg(F.sum("growth").alias("g"), F.max("down").alias("drawdown"))
    out = total.join(per, list(by), "left")
    n = F.coalesce("trades", F.lit(0))
    return out.select(*by, n.cast("long").alias("trades"), F.when(n > 0, F.col("wins") / n).alias("hit_rate"), (F.exp("g") - 1).alias("profit"), "drawdown")


def simulate(strategy: Strategy, price: SeriesFrame, start: int | None = None, end: int | None = None) -> DataFrame:
    """Summary of a strategy on each series between two entries; indicators may look further back."""
    ev = strategy.events(price)
    if start is not None:
        ev = ev.where(F.col("idx") >= start)
    if end is not None:
        ev = ev.where(F.col("idx") <= end)
    return summarize(positions(ev))


def simulate_units(strategy: Strategy, price: SeriesFrame, units: tuple[str, ...] = ("day", "hour", "minute"), hours_per_day: float = 8.5) -> DataFrame:
    """The summary of a strategy given in days at several granularities: the last price of each unit, windows as long in
    time. Adds the column unit."""
    out = None
    for unit in units:
        at = price if unit == price.calendar.unit else price.reduce(unit, "last")
        one = simulate(strategy.scaled(unit, hours_per_day), at).withColumn("unit", F.lit(unit))
        out = one if out is None else out.unionByName(one)
    return out


def evaluate_grid(spark: SparkSession, strategies: list[Strategy], price: SeriesFrame, top: int = 10) -> DataFrame:
    """All strategies on all series at once, the best of each strategy ranked.

    Each distinct window is computed once as a column; strategies are rows of a parameter table (as long as the
    grid) that pick their columns, so the number of jobs and shuffles doesn't grow with the grid."""
    df = price.df
    frames = sorted({x for s in strategies for x in (s.short, s.long)})
    v = F.col("v")
    for w in frames:
        df = df.withColumn(f"m{w}", window.agg_over(v, F.avg, window.over(price, w)))
    lines = sorted({(s.short, s.long, s.smooth) for s in strategies})
    base = price.with_df(df)
    for a, b, m in lines:
        df = df.withColumn(f"l{a}_{b}_{m}", F.avg(F.col(f"m{a}") - F.col(f"m{b}")).over(window.over(base, m)))

    def picks(s: Strategy) -> Column:
        sell = nulls.divide(F.col(f"m{s.long}"), F.col(f"m{s.short}")) > s.factor
        event = F.when(F.coalesce(sell, F.lit(False)), 0).when(F.col(f"l{s.short}_{s.long}_{s.smooth}") > 0, 1)
        label = f"{s.short}/{s.long}/{s.smooth}/{s.factor:g}"
        return F.struct(F.lit(label).alias("strategy"), event.alias("event"))

    rows = df.select("series_id", "idx", "v", F.inline(F.array(*[picks(s) for s in strategies])))
    by = ("strategy", "series_id")
    summed = summarize(positions(rows, by), by)
    rank = F.row_number().over(Window.partitionBy("strategy").orderBy(F.desc(F.round("profit", 9)), "series_id"))
    return summed.withColumn("rank", rank).where(F.col("rank") <= top)
