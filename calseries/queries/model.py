"""Queries on the data model: construction, calendars, nulls, vector space and relational-like operators."""

from __future__ import annotations

import datetime as dt

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import nulls
from ..calendar import Calendar
from ..operators import algebra as A
from ..operators import window as W
from ..series import SeriesFrame, result, snap
from ..sources import base as B
from .text import registry, BY_TYPE, HOLES, HOURLY, LEVEL, MINUTES, QUOTE, STOCK, TICKS, kind, series

QUERIES, ORACLES, query = registry()
E1, E2, E3 = "click", "view", "purchase"


def two(s: SparkSession, d: str) -> tuple[SeriesFrame, SeriesFrame]:
    return B.of_type(s, d, E1), B.of_type(s, d, E2)


TWO = f"{kind(E1, 1)}, {kind(E2, 2)}"
THREE = f"{TWO}, {kind(E3, 3)}"
BOTH = "SELECT series_id, idx, e1.v AS a, e2.v AS b FROM e1 JOIN e2 USING (series_id, idx)"

# ---- construction and calendars ----------------------------------------------------------------------------------------

query("series_daily_orders", series(LEVEL, "SELECT * FROM level"))(lambda s, d: result(B.level(s, d)))
query("series_hourly_events", series(HOURLY, "SELECT * FROM hourly"))(lambda s, d: result(B.hourly(s, d)))


@query("calendar_regular", "SELECT CAST(i AS BIGINT) AS idx, lo + to_hours(CAST(i AS BIGINT)) AS t FROM (SELECT lo, unnest(range(date_diff('hour', lo, hi) + 1)) AS i FROM (SELECT date_trunc('hour', min(ts)) AS lo, max(ts) AS hi FROM events))")
def calendar_regular(s: SparkSession, d: str) -> DataFrame:
    return Calendar.spanning(B.read_table(s, d, "events", ["ts"]), "ts", "hour")


@query("calendar_open_days", "SELECT CAST(row_number() OVER (ORDER BY t) - 1 AS BIGINT) AS idx, t FROM (SELECT DISTINCT o_orderdate AS t FROM orders)")
def calendar_open_days(s: SparkSession, d: str) -> DataFrame:
    return Calendar.from_times(B.read_table(s, d, "orders", ["o_orderdate"]), "o_orderdate")


query("slice_interval", series(LEVEL, "SELECT * FROM level WHERE idx BETWEEN 400 AND 900"))(lambda s, d: result(B.level(s, d).slice(400, 900)))
query("tick_index", series(TICKS, "SELECT * FROM ticks"))(lambda s, d: result(B.ticks(s, d)))
query("calendar_expand", series(LEVEL, "SELECT series_id, idx * 4 + k AS idx, v FROM level CROSS JOIN range(4) g(k)".replace("* 4", "* 24").replace("range(4)", "range(24)")))(
    lambda s, d: result(B.level(s, d).expand("hour")))
query("calendar_expand_linear", series(LEVEL, """SELECT series_id, idx * 24 + k AS idx, CASE WHEN nv IS NULL THEN v ELSE v + (nv - v) * k / ((ni - idx) * 24) END AS v
  FROM (SELECT *, lead(v) OVER (ORDER BY idx) AS nv, lead(idx) OVER (ORDER BY idx) AS ni FROM level) CROSS JOIN range(24) g(k) WHERE nv IS NOT NULL OR k = 0"""))(
    lambda s, d: result(B.level(s, d).expand("hour", "linear")))
query("reduce_minute_hour", series(MINUTES, "SELECT series_id, idx // 60 AS idx, avg(v) AS v FROM mins GROUP BY ALL"))(lambda s, d: result(B.event_minutes(s, d).reduce("hour", "avg")))
query("reduce_day_month", series(LEVEL, """SELECT series_id, date_diff('month', DATE '1995-01-01', DATE '1995-01-01' + CAST(idx AS INTEGER)) AS idx, max(v) AS v FROM level GROUP BY ALL"""))(
    lambda s, d: result(B.level(s, d).reduce("month", "max")))
query("reduce_first_last", series(MINUTES, "SELECT series_id, idx // 1440 AS idx, arg_max(v, idx) - arg_min(v, idx) AS v FROM mins GROUP BY ALL"))(
    lambda s, d: result(B.event_minutes(s, d).reduce("day", "last") - B.event_minutes(s, d).reduce("day", "first")))


@query("ohlc_daily", f"WITH {QUOTE} SELECT series_id, CAST(idx AS BIGINT) AS idx, open, high, low, close, CAST(volume AS BIGINT) AS volume FROM quote")
def ohlc_daily(s: SparkSession, d: str) -> DataFrame:
    return B.quote_daily(s, d).df.withColumn("volume", F.col("volume").cast("long"))


query("densify_daily", series(LEVEL, "SELECT 'level' AS series_id, i AS idx, v FROM range(2405) g(i) LEFT JOIN level ON idx = i"))(lambda s, d: result(B.level(s, d).densify()))


@query("null_states", f"WITH {HOLES} SELECT CASE WHEN isnan(v) THEN 'unknown' ELSE 'value' END AS state, count(*) AS n FROM holes GROUP BY ALL UNION ALL SELECT 'empty', 2405 - count(*) FROM holes")
def null_states(s: SparkSession, d: str) -> DataFrame:
    return B.level_holes(s, d).densify().states().groupBy("state").agg(F.count(F.lit(1)).alias("n"))


query("fill_previous", series(LEVEL, "SELECT 'level' AS series_id, i AS idx, last_value(v IGNORE NULLS) OVER (ORDER BY i) AS v FROM range(2405) g(i) LEFT JOIN level ON idx = i"))(
    lambda s, d: result(B.level(s, d).densify().fill("previous")))
query("fill_value", series(LEVEL, "SELECT 'level' AS series_id, i AS idx, coalesce(v, 0) AS v FROM range(2405) g(i) LEFT JOIN level ON idx = i"))(
    lambda s, d: result(B.level(s, d).densify().fill("value", 0.0)))
query("fill_linear", series(LEVEL, """SELECT series_id, idx, coalesce(v, pv + (nv - pv) * (idx - pi) / (ni - pi)) AS v FROM (SELECT 'level' AS series_id, i AS idx, v,
  last_value(v IGNORE NULLS) OVER p AS pv, first_value(v IGNORE NULLS) OVER n AS nv, last_value(CASE WHEN v IS NOT NULL THEN i END IGNORE NULLS) OVER p AS pi, first_value(CASE WHEN v IS NOT NULL THEN i END IGNORE NULLS) OVER n AS ni
  FROM range(2405) g(i) LEFT JOIN level ON idx = i WINDOW p AS (ORDER BY i ROWS UNBOUNDED PRECEDING), n AS (ORDER BY i ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))"""))(
    lambda s, d: result(B.level(s, d).densify().fill("linear")))

GRID = "g AS (SELECT CAST(4 * i + j AS BIGINT) AS idx, [2.0, -1.5, NULL, 'nan'::DOUBLE][i + 1] AS a, [2.0, -1.5, NULL, 'nan'::DOUBLE][j + 1] AS b FROM range(4) x(i), range(4) y(j))"


def grid_sql(expr: str, a: str = "a", b: str = "b") -> str:
    unk = f"(coalesce(isnan({a}), false) OR coalesce(isnan({b}), false))"
    emp = f"({a} IS NULL OR {b} IS NULL)"
    return f"WITH {GRID} SELECT idx, CASE WHEN {unk} THEN 'unknown' WHEN {emp} THEN 'empty' ELSE 'value' END AS state, CASE WHEN NOT {unk} AND NOT {emp} THEN {expr} END AS v FROM g"


def grid(fn):
    def run(s: SparkSession, d: str) -> DataFrame:
        g = B.null_grid(s).withColumn("r", nulls.lift(fn, F.col("a"), F.col("b")))
        return g.select("idx", nulls.state(F.col("r")).alias("state"), F.when(~nulls.is_unknown(F.col("r")), F.col("r")).alias("v"))

    return run


query("null_add_table", grid_sql("a + b"))(grid(lambda a, b: a + b))
query("null_mult_table", grid_sql("a * b"))(grid(lambda a, b: a * b))
query("null_divide_table", grid_sql("a / b"))(grid(nulls.divide))


@query("null_scale_table", f"WITH {GRID} SELECT idx, CASE WHEN isnan(a) THEN 'unknown' WHEN a IS NULL THEN 'empty' ELSE 'value' END AS state, CASE WHEN NOT isnan(a) THEN a * 3 END AS v FROM g")
def null_scale_table(s: SparkSession, d: str) -> DataFrame:
    r = F.col("a") * F.lit(3.0)
    return B.null_grid(s).select("idx", nulls.state(r).alias("state"), F.when(~nulls.is_unknown(r), r).alias("v"))


query("vector_identity", series(LEVEL, "SELECT series_id, idx, v + 0 AS v FROM level"))(lambda s, d: result(A.plus(B.level(s, d), A.constant(B.level(s, d), 0.0))))


@query("series_metadata", f"WITH {BY_TYPE} SELECT series_id, count(v) AS entries, CAST(min(idx) AS BIGINT) AS first_idx, CAST(max(idx) AS BIGINT) AS last_idx, '2024-01-01T00:00:00/hour/720' AS calendar FROM hbt GROUP BY ALL")
def series_metadata(s: SparkSession, d: str) -> DataFrame:
    return B.hourly_by_type(s, d).describe()


# ---- vector space ------------------------------------------------------------------------------------------------------

query("vec_plus", series(TWO, f"SELECT series_id, idx, a + b AS v FROM ({BOTH})"))(lambda s, d: result(A.plus(*two(s, d))))
query("vec_minus", series(TWO, f"SELECT series_id, idx, a - b AS v FROM ({BOTH})"))(lambda s, d: result(A.minus(*two(s, d))))
query("vec_mult", series(TWO, f"SELECT series_id, idx, a * b AS v FROM ({BOTH})"))(lambda s, d: result(A.mult(*two(s, d))))
query("vec_divide", series(TWO, f"SELECT series_id, idx, CASE WHEN b = 0 THEN 'nan'::DOUBLE ELSE a / b END AS v FROM ({BOTH})"))(lambda s, d: result(A.ratio(*two(s, d))))
query("vec_scale", series(LEVEL, "SELECT series_id, idx, v * 2.5 AS v FROM level"))(lambda s, d: result(B.level(s, d) * 2.5))
query("vec_linear_comb", series(THREE, "SELECT series_id, idx, 2 * e1.v - 0.5 * e2.v + e3.v AS v FROM e1 JOIN e2 USING (series_id, idx) JOIN e3 USING (series_id, idx)"))(
    lambda s, d: result(A.linear([(2.0, B.of_type(s, d, E1)), (-0.5, B.of_type(s, d, E2)), (1.0, B.of_type(s, d, E3))])))
query("vec_divide_zero", series(LEVEL, "SELECT series_id, idx, CASE WHEN idx % 5 = 0 THEN 'nan'::DOUBLE ELSE v / (idx % 5) END AS v FROM level"))(
    lambda s, d: result(A.ratio(B.level(s, d), (lambda a: a.with_df(a.df.withColumn("v", (F.col("idx") % 5).cast("double"))))(B.level(s, d)))))
query("proj_math", series(LEVEL, "SELECT series_id, idx, CASE WHEN v > 100000 THEN ln(v - 100000) ELSE 'nan'::DOUBLE END AS v FROM level", 6))(
    lambda s, d: result(A.map_values(B.level(s, d), lambda v: F.ln(v - 100000)), 6))
query("shift_1", series(LEVEL, "SELECT series_id, idx + 1 AS idx, v FROM level WHERE idx + 1 < 2405"))(lambda s, d: result(A.shift(B.level(s, d), 1)))


@query("vec_dot_norm", f"WITH {TWO} SELECT series_id, round(sum(a * b), 4) AS dot, round(sqrt(sum((a - b) * (a - b))), 6) AS distance FROM ({BOTH}) GROUP BY ALL")
def vec_dot_norm(s: SparkSession, d: str) -> DataFrame:
    a, b = two(s, d)
    return A.dot(a, b).join(A.norm(A.minus(a, b)), "series_id").select("series_id", snap(F.col("dot"), 4).alias("dot"), snap(F.col("norm"), 6).alias("distance"))


@query("axiom_distributive", "SELECT CAST(0 AS BIGINT) AS differing")
def axiom_distributive(s: SparkSession, d: str) -> DataFrame:
    a, b = two(s, d)
    x, y = (a + b) * 3.0, a * 3.0 + b * 3.0
    rows = A.wide([x, y])
    bad = rows.where(F.col("v0").isNull() | F.col("v1").isNull() | (F.abs(F.col("v0") - F.col("v1")) > 1e-9))
    return bad.agg(F.count(F.lit(1)).alias("differing"))


# ---- selection, projection, sets, joins -------------------------------------------------------------------------------

query("sel_gt", series(HOLES, "SELECT * FROM holes WHERE v > 250000 OR isnan(v)"))(lambda s, d: result(A.select(B.level_holes(s, d), lambda v: v > 250000)))
query("sel_gt_drop_unknown", series(HOLES, "SELECT * FROM holes WHERE v > 250000 AND NOT isnan(v)"))(lambda s, d: result(A.select(B.level_holes(s, d), lambda v: v > 250000, "empty")))
query("sel_between", series(LEVEL, "SELECT * FROM level WHERE v BETWEEN 240000 AND 260000"))(lambda s, d: result(A.select(B.level(s, d), lambda v: v.between(240000, 260000))))
query("sel_in", series(HOURLY, "SELECT * FROM hourly WHERE floor(v) IN (48, 50, 52)"))(lambda s, d: result(A.select(B.hourly(s, d), lambda v: F.floor(v).isin(48, 50, 52))))
query("sel_time_hours", series(HOURLY, "SELECT * FROM hourly WHERE hour(TIMESTAMP '2024-01-01' + to_hours(CAST(idx AS BIGINT))) BETWEEN 9 AND 17"))(
    lambda s, d: result(A.select_time(B.hourly(s, d), lambda t: F.hour(t).between(9, 17))))
query("mask_by_series", series(TWO, f"SELECT series_id, idx, a AS v FROM ({BOTH}) WHERE b > 50"))(lambda s, d: result(A.mask(*two(s, d), lambda v: v > 50)))
query("proj_affine", series(HOLES, "SELECT series_id, idx, 2 * v + 1 AS v FROM holes"))(lambda s, d: result(A.project(B.level_holes(s, d), lambda v: 2 * v + 1)))
query("proj_null_override", series(HOLES, "SELECT 'level' AS series_id, i AS idx, CASE WHEN v IS NULL THEN -1 WHEN isnan(v) THEN -2 ELSE v / 2 END AS v FROM range(2405) g(i) LEFT JOIN holes ON idx = i"))(
    lambda s, d: result((lambda a: a.with_df(a.df.withColumn("series_id", F.lit("level"))))(A.project(B.level_holes(s, d).densify(), lambda v: v / 2, on_empty=-1.0, on_unknown=-2.0))))
query("series_union", series(TWO, "SELECT series_id, idx, coalesce(e1.v, e2.v) AS v FROM e1 FULL JOIN e2 USING (series_id, idx)"))(lambda s, d: result(A.union(*two(s, d))))
query("series_union_unknown", series(TWO, "SELECT series_id, idx, CASE WHEN e1.v <> e2.v THEN 'nan'::DOUBLE ELSE coalesce(e1.v, e2.v) END AS v FROM e1 FULL JOIN e2 USING (series_id, idx)"))(
    lambda s, d: result(A.union(*two(s, d), "unknown")))
query("series_intersect", series(TWO, f"SELECT series_id, idx, a AS v FROM ({BOTH}) WHERE abs(a - b) <= 5"))(lambda s, d: result(A.intersect(*two(s, d), tol=5.0)))
query("series_intersect_time", series(TWO, f"SELECT series_id, idx, a AS v FROM ({BOTH})"))(lambda s, d: result(A.intersect(*two(s, d), match="time")))
query("series_except", series(TWO, "SELECT * FROM e1 ANTI JOIN e2 USING (series_id, idx)"))(lambda s, d: result(A.minus_entries(*two(s, d))))
query("join2_fun", series(TWO, f"SELECT series_id, idx, sqrt(a * a + b * b) AS v FROM ({BOTH})", 6))(lambda s, d: result(A.join([*two(s, d)], lambda a, b: F.sqrt(a * a + b * b)), 6))
AVG3 = series(THREE, "SELECT series_id, idx, (e1.v + e2.v + e3.v) / 3 AS v FROM e1 JOIN e2 USING (series_id, idx) JOIN e3 USING (series_id, idx)", 5)
query("join3_fun", AVG3)(lambda s, d: result(A.join([*two(s, d), B.of_type(s, d, E3)], "AVG"), 5))
query("join_binary_chain", AVG3)(lambda s, d: result(A.join([*two(s, d), B.of_type(s, d, E3)], "AVG", strategy="binary"), 5))


@query("join_kary_pivot", f"WITH {BY_TYPE} SELECT CAST(idx AS BIGINT) AS idx, count(*) AS n, round(max(v) - min(v), 4) AS spread FROM hbt GROUP BY idx")
def join_kary_pivot(s: SparkSession, d: str) -> DataFrame:
    return B.hourly_by_type(s, d).df.groupBy("idx").agg(F.count(F.lit(1)).alias("n"), snap(F.max("v") - F.min("v"), 4).alias("spread"))


query("join_sum", series(TWO, f"SELECT series_id, idx, a + b AS v FROM ({BOTH})"))(lambda s, d: result(A.join([*two(s, d)], "SUM")))


@query("join_on_value", f"WITH {TWO} SELECT e1.idx::BIGINT AS a_idx, e2.idx::BIGINT AS b_idx, round(e1.v, 4) AS a_v, round(e2.v, 4) AS b_v FROM e1 JOIN e2 ON abs(e1.v - e2.v) <= 0.05")
def join_on_value(s: SparkSession, d: str) -> DataFrame:
    return A.join_values(*two(s, d), 0.05).select("a_idx", "b_idx", snap(F.col("a_v"), 4).alias("a_v"), snap(F.col("b_v"), 4).alias("b_v"))


query("excess_over_index", series(f"{STOCK}, ref AS (SELECT date_diff('day', TIMESTAMP '1995-01-02', l_shipdate) AS idx, avg(l_extendedprice) AS r FROM lineitem GROUP BY ALL)", "SELECT series_id, idx, v - r AS v FROM stock JOIN ref USING (idx)"))(
    lambda s, d: result(A.join_reference(B.stock_daily(s, d), SeriesFrame.of(B.read_table(s, d, "lineitem", ["l_shipdate", "l_extendedprice"]), None, "l_shipdate", "l_extendedprice", B.SHIPS), lambda v, r: v - r)))
query("expr_compose", series(LEVEL, f"SELECT series_id, idx, 2 * v - avg(v) OVER (PARTITION BY series_id ORDER BY idx RANGE BETWEEN 4 PRECEDING AND CURRENT ROW) AS v FROM level"))(
    lambda s, d: result((lambda a: a * 2.0 - W.mavg(a, 5))(B.level(s, d))))
