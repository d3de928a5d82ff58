"""Nulls, calendars, axioms, published golden values."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from calseries import nulls
from calseries.calendar import Calendar, unit_window
from calseries.operators import algebra as A
from calseries.operators import strategy as S
from calseries.operators import window as W
from calseries.series import SeriesFrame
from calseries.sources import base as B

from .conftest import SMALL

NAN = float("nan")


def make(spark, rows, n=10):
    cal = Calendar.regular("2024-01-01", "day", n)
    return SeriesFrame(spark.createDataFrame([("s", i, v) for i, v in rows], "series_id string, idx long, v double"), cal)


def values(sf):
    return {r["idx"]: r["v"] for r in sf.df.collect()}


def test_null_lattice(spark):
    df = B.null_grid(spark).select("a", "b", nulls.combine(F.col("a"), F.col("b")).alias("s"))
    for r in df.collect():
        unknown = any(x is not None and x != x for x in (r["a"], r["b"]))
        empty = r["a"] is None or r["b"] is None
        assert r["s"] == ("unknown" if unknown else "empty" if empty else "value")


def test_unknown_is_never_selected_as_large(spark):
    a = make(spark, [(0, 1.0), (1, NAN), (2, 5.0)])
    assert set(values(A.select(a, lambda v: v > 2, "empty"))) == {2}
    assert set(values(A.select(a, lambda v: v > 2))) == {1, 2}


def test_moving_minimum_sees_unknown(spark):
    got = values(W.mmin(make(spark, [(0, 1.0), (1, NAN), (2, 5.0), (3, 4.0)]), 2))
    assert got[0] == 1.0 and got[1] != got[1] and got[2] != got[2] and got[3] == 4.0


def test_vector_space(spark):
    a, b, c = (make(spark, [(i, float((i * k) % 7)) for i in range(10)]) for k in (1, 2, 3))
    same = lambda x, y: values(x) == values(y)
    assert same(a + b, b + a)
    assert same((a + b) + c, a + (b + c))
    assert same((a + b) * 2.0, a * 2.0 + b * 2.0)
    assert same(a + A.constant(a, 0.0), a)
    assert set(values(a - a).values()) == {0.0}


def test_other_calendar_is_refused(spark):
    a = make(spark, [(0, 1.0)])
    with pytest.raises(ValueError):
        A.plus(a, SeriesFrame(a.df, Calendar.regular("2024-01-01", "hour")))


def test_constant_is_a_fixed_point(spark):
    a = B.ramp(spark, 50, "constant")
    for method in ("sliding", "prefix", "packed", "pandas", "selfjoin"):
        assert set(values(W.mavg(a, 7, method)).values()) == {5.0}
    assert all(v != v for v in values(W.rsi(a, 3)).values())


def test_lagged_window_excludes_now(spark):
    got = values(W.win(make(spark, [(i, float(i)) for i in range(5)]), F.sum, 2))
    assert got == {1: 0.0, 2: 1.0, 3: 3.0, 4: 5.0}


def test_windows_respect_holes(spark):
    a = make(spark, [(0, 2.0), (5, 4.0), (6, 6.0)])
    for method in ("sliding", "prefix", "packed"):
        assert values(W.mavg(a, 3, method)) == {0: 2.0, 5: 4.0, 6: 5.0}


def test_calendar_arithmetic():
    assert [unit_window(9, u) for u in ("day", "hour", "minute")] == [9, 72, 4590]
    assert unit_window(360, "minute") == 183_600 and 3243 * unit_window(1, "minute") == 1_653_930


def test_calendar_round_trip(spark):
    for unit in ("minute", "hour", "day", "week", "month"):
        cal = Calendar.regular(dt.datetime(2023, 11, 1), unit, 20)
        rows = cal.frame(spark).select("idx", cal.index_of(F.col("t")).alias("back")).collect()
        assert all(r["idx"] == r["back"] for r in rows) and len(rows) == 20


def test_golden(spark):
    level = B.level(spark, SMALL)
    close = lambda x, y: abs(x - y) <= 1e-9 * abs(y)
    total = lambda sf: sf.df.agg(F.sum("v")).first()[0]
    assert close(total(level), 273177231.3455)
    assert close(total(W.mavg(level, 50)), 272630714.174823)
    buy, sell = S.buy_macd(level), S.sell_ratio(level)
    assert buy.df.count() == 548 and close(total(buy), 14596633.227746)
    assert sell.df.count() == 306 and abs(total(sell) - 398.006035) < 1e-5
    t = B.ticks(spark, SMALL)
    assert close(total(W.mavg(t, 100)), 317229539.065007)
    assert abs(W.rsi(t, 50).df.where("NOT isnan(v)").agg(F.sum("v")).first()[0] - 300260.893512) < 1e-3


def test_position_is_that_of_the_last_event(spark):
    ev = spark.createDataFrame([("s", i, float(10 + i), e) for i, e in enumerate([None, 1, None, 0, None, 1])], "series_id string, idx long, v double, event int")
    pos = S.positions(ev)
    assert [r["position"] for r in pos.orderBy("idx").collect()] == [0, 1, 1, 0, 0, 1]
    one = S.summarize(pos).first()
    assert one["trades"] == 2 and abs(one["profit"] - (13 / 11 - 1)) < 1e-12


def test_files_keep_nulls(spark, tmp_path):
    a = make(spark, [(0, 1.5), (2, NAN), (3, -2.0)])
    for fmt in ("xml", "csv", "json", "orc", "parquet"):
        B.write_series(a, fmt, str(tmp_path / fmt))
        got = values(B.read_series(spark, fmt, str(tmp_path / fmt), a.calendar))
        assert set(got) == {0, 2, 3} and got[0] == 1.5 and got[2] != got[2] and got[3] == -2.0
