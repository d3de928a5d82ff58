"""Queries on strategies and driving indicators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import algebra as A
from ..operators import strategy as S
from ..operators import trips as T
from ..series import SeriesFrame, result, snap
from ..sources import base as B
from .text import HOURLY, LEVEL, MINUTES, SUPPLIER, TRIPS, TRIPS8, frame, registry, series

QUERIES, ORACLES, query = registry()


def line_sql(t: str, short: int = 12, long: int = 26, smooth: int = 9) -> str:
    return f"SELECT series_id, idx, avg(m) OVER {frame(smooth)} AS v FROM (SELECT series_id, idx, avg(v) OVER {frame(short)} - avg(v) OVER {frame(long)} AS m FROM {t})"


def ratio_sql(t: str, short: int = 12, long: int = 26) -> str:
    return f"SELECT series_id, idx, avg(v) OVER {frame(long)} / avg(v) OVER {frame(short)} AS v FROM {t}"


query("strategy_buy", series(LEVEL, f"SELECT * FROM ({line_sql('level')}) WHERE v > 1e-9", 3))(lambda s, d: result(A.select(S.buy_macd(B.level(s, d)), lambda v: v > 1e-9), 3))
query("strategy_sell", series(LEVEL, f"SELECT * FROM ({ratio_sql('level')}) WHERE v > 1.1", 6))(lambda s, d: result(S.sell_ratio(B.level(s, d)), 6))
query("supplier_buy", series(SUPPLIER, f"SELECT * FROM ({line_sql('supp')}) WHERE v > 1e-6", 3))(lambda s, d: result(A.select(S.buy_macd(B.supplier_daily(s, d)), lambda v: v > 1e-6), 3))
query("supplier_sell", series(SUPPLIER, f"SELECT * FROM ({ratio_sql('supp')}) WHERE v > 1.1", 6))(lambda s, d: result(S.sell_ratio(B.supplier_daily(s, d)), 6))


def events_sql(cte: str, t: str, factor: float = 1.1, short: int = 12, long: int = 26, smooth: int = 9) -> str:
    return f"""{cte}, l AS ({line_sql(t, short, long, smooth)}), q AS ({ratio_sql(t, short, long)}),
  ev AS (SELECT p.series_id, p.idx, p.v, CASE WHEN q.v > {factor} THEN 0 WHEN l.v > 0 THEN 1 END AS event FROM {t} p JOIN l USING (series_id, idx) JOIN q USING (series_id, idx)),
  pos AS (SELECT *, coalesce(last_value(event IGNORE NULLS) OVER (PARTITION BY series_id ORDER BY idx ROWS UNBOUNDED PRECEDING), 0) AS position FROM ev)"""


def summary_sql(pos: str, by: str = "series_id") -> str:
    w = f"(PARTITION BY {by} ORDER BY idx)"
    run = f"(PARTITION BY {by} ORDER BY idx ROWS UNBOUNDED PRECEDING)"
    return f""", st AS (SELECT *, coalesce(lag(position) OVER {w}, 0) AS was, ln(v / lag(v) OVER {w}) AS step FROM {pos}),
  s2 AS (SELECT *, CASE WHEN was = 1 THEN step ELSE 0 END AS growth, sum(CASE WHEN position = 1 AND was = 0 THEN 1 ELSE 0 END) OVER {run} AS trade FROM st),
  s3 AS (SELECT *, sum(growth) OVER {run} AS level_ FROM s2),
  s4 AS (SELECT *, 1 - exp(level_ - greatest(0, max(level_) OVER {run})) AS down FROM s3),
  tr AS (SELECT {by}, trade, sum(growth) AS g FROM s4 WHERE trade > 0 GROUP BY ALL),
  per AS (SELECT {by}, count(*) AS trades, count(*) FILTER (g > 0) AS wins FROM tr GROUP BY ALL),
  tot AS (SELECT {by}, sum(growth) AS g, max(down) AS drawdown FROM s4 GROUP BY ALL)"""


ROUNDED = ("hit_rate", "profit", "drawdown")


def rounded(df: DataFrame) -> DataFrame:
    return df.withColumns({c: snap(F.col(c), 6) for c in ROUNDED if c in df.columns})


@query("strategy_events", f"WITH {events_sql(LEVEL, 'level')} SELECT series_id, CAST(idx AS BIGINT) AS idx, CASE event WHEN 1 THEN 'buy' WHEN 0 THEN 'sell' END AS event FROM ev WHERE event IS NOT NULL")
def strategy_events(s: SparkSession, d: str) -> DataFrame:
    ev = S.Strategy().events(B.level(s, d)).where("event IS NOT NULL")
    return ev.select("series_id", "idx", F.when(F.col("event") == 1, "buy").otherwise("sell").alias("event"))


@query("strategy_positions", f"WITH {events_sql(SUPPLIER, 'supp')} SELECT series_id, CAST(idx AS BIGINT) AS idx, CAST(position AS INTEGER) AS position FROM pos")
def strategy_positions(s: SparkSession, d: str) -> DataFrame:
    return S.positions(S.Strategy().events(B.supplier_daily(s, d))).select("series_id", "idx", F.col("position").cast("int").alias("position"))


PNL = "SELECT series_id, coalesce(trades, 0) AS trades, round(CAST(wins AS DOUBLE) / trades, 6) AS hit_rate, round(exp(g) - 1, 6) AS profit, round(drawdown, 6) AS drawdown FROM tot LEFT JOIN per USING (series_id)"


@query("strategy_pnl", f"WITH {events_sql(SUPPLIER, 'supp')}{summary_sql('pos')} {PNL}")
def strategy_pnl(s: SparkSession, d: str) -> DataFrame:
    return rounded(S.simulate(S.Strategy(), B.supplier_daily(s, d)))


@query("strategy_pnl_interval", f"WITH {events_sql(LEVEL, 'level')}, cut AS (SELECT series_id, idx, v, event, coalesce(last_value(event IGNORE NULLS) OVER (PARTITION BY series_id ORDER BY idx ROWS UNBOUNDED PRECEDING), 0) AS position FROM ev WHERE idx BETWEEN 500 AND 1500){summary_sql('cut')} {PNL}")
def strategy_pnl_interval(s: SparkSession, d: str) -> DataFrame:
    return rounded(S.simulate(S.Strategy(), B.level(s, d), 500, 1500))


#: A strategy in days, at each unit: its table of prices and its windows there.
UNITS = {"day": (1440, 2, 5, 2), "hour": (60, 16, 40, 16), "minute": (1, 1020, 2550, 1020)}
UNIT_SQL = " UNION ALL ".join(
    f"SELECT *, '{u}' AS unit FROM (WITH {events_sql(f'{MINUTES}, px AS (SELECT series_id, idx // {n} AS idx, arg_max(v, idx) AS v FROM mins GROUP BY ALL)', 'px', 1.1, a, b, c)}{summary_sql('pos')} {PNL})" for u, (n, a, b, c) in UNITS.items())


@query("strategy_units", UNIT_SQL)
def strategy_units(s: SparkSession, d: str) -> DataFrame:
    return rounded(S.simulate_units(S.Strategy(2, 5, 2), B.event_minutes(s, d)))


GRID = [S.Strategy(a, b, m, f) for a, b in ((5, 20), (12, 26)) for m in (5, 9) for f in (1.1, 1.3)]


def grid_sql() -> str:
    cols = [f"SELECT '{g.short}/{g.long}/{g.smooth}/{g.factor:g}' AS strategy, p.series_id, p.idx, p.v, CASE WHEN q.v > {g.factor} THEN 0 WHEN l.v > 0 THEN 1 END AS event FROM supp p JOIN ({line_sql('supp', g.short, g.long, g.smooth)}) l USING (series_id, idx) JOIN ({ratio_sql('supp', g.short, g.long)}) q USING (series_id, idx)" for g in GRID]
    return f"""WITH {SUPPLIER}, ev AS ({' UNION ALL '.join(cols)}),
  pos AS (SELECT *, coalesce(last_value(event IGNORE NULLS) OVER (PARTITION BY strategy, series_id ORDER BY idx ROWS UNBOUNDED PRECEDING), 0) AS position FROM ev){summary_sql('pos', 'strategy, series_id')},
  al AS (SELECT strategy, series_id, coalesce(trades, 0) AS trades, CAST(wins AS DOUBLE) / trades AS hit_rate, exp(g) - 1 AS profit, drawdown FROM tot LEFT JOIN per USING (strategy, series_id)),
  rk AS (SELECT *, CAST(row_number() OVER (PARTITION BY strategy ORDER BY round(profit, 9) DESC, series_id) AS INTEGER) AS rank FROM al)
  SELECT strategy, series_id, trades, round(hit_rate, 6) AS hit_rate, round(profit, 6) AS profit, round(drawdown, 6) AS drawdown, rank FROM rk WHERE rank <= 5"""


@query("strategy_grid_topk", grid_sql())
def strategy_grid_topk(s: SparkSession, d: str) -> DataFrame:
    return rounded(S.evaluate_grid(s, GRID, B.supplier_daily(s, d), top=5))


query("strategy_hourly", series(HOURLY, f"SELECT * FROM ({line_sql('hourly')}) WHERE v > 1e-9", 5))(lambda s, d: result(A.select(S.buy_macd(B.hourly(s, d)), lambda v: v > 1e-9), 5))

# ---- trips ---------------------------------------------------------------------------------------------------------------


def trips_sql(cte: str, brake: float = T.BRAKE) -> str:
    w = "(PARTITION BY trip_id ORDER BY t, event_id)"
    return f"""WITH {cte},
  a AS (SELECT *, lag(v) OVER {w} AS v0, t - lag(t) OVER {w} AS dt FROM trips),
  b AS (SELECT *, v - v0 AS dv, CASE WHEN dt > 0 THEN (v - v0) / dt END AS a, v < 2 AS still FROM a),
  c AS (SELECT *, coalesce(a < {brake}, false) AS braking, coalesce(a < 0, false) AS slower, coalesce(lag(still) OVER {w}, false) AS was_still, coalesce(sign(dv) * sign(lag(dv) OVER {w}) < 0, false) AS turn,
      coalesce(gear <> lag(gear) OVER {w}, false) AS shift FROM b),
  d AS (SELECT *, braking AND NOT coalesce(lag(braking) OVER {w}, false) AS brake_on, slower AND NOT coalesce(lag(slower) OVER {w}, false) AS slow_on, slower AND NOT coalesce(lead(slower) OVER {w}, false) AS slow_off FROM c),
  e AS (SELECT *, sum(CASE WHEN slow_on THEN 1 ELSE 0 END) OVER (PARTITION BY trip_id ORDER BY t, event_id ROWS UNBOUNDED PRECEDING) AS run FROM d),
  f AS (SELECT *, max(CASE WHEN slow_off AND still THEN 1 ELSE 0 END) OVER (PARTITION BY trip_id, run) AS hits FROM e),
  g AS (SELECT trip_id, count(*) AS n, sum(dt) AS duration, sum(v * dt / 3600) AS distance, avg(v) AS avg_speed, avg(v) FILTER (NOT still) AS avg_driving_speed, avg(a) AS avg_accel, avg(a) FILTER (a > 0) AS avg_positive_accel,
    sum(v * greatest(a, 0) * dt) AS power, sum(CASE WHEN dv > 0 THEN v * v - v0 * v0 ELSE 0 END) AS rises, sum(CASE WHEN still THEN dt ELSE 0 END) AS standing, count(*) FILTER (still AND NOT was_still) AS stops,
    count(*) FILTER (brake_on) AS brakes, count(*) FILTER (shift) AS gear_shifts, count(*) FILTER (turn) AS extrema, sum(v0 * dt / 3600) FILTER (slower AND hits = 1) AS braked, count(*) FILTER (slow_off AND still) AS run_stops, avg(rpm) AS avg_rpm
    FROM f GROUP BY trip_id)"""


COLUMNS = {
    "eco_avg_speed": {"avg_speed": "avg_speed", "avg_driving_speed": "avg_driving_speed"},
    "eco_accel": {"avg_accel": "avg_accel", "avg_positive_accel": "avg_positive_accel"},
    "eco_rpa": {"rpa": "power / nullif(duration, 0)"}, "eco_rpa_distance": {"rpa_distance": "power / nullif(distance, 0)"},
    "eco_pke": {"pke": "rises / nullif(duration, 0)", "pke_distance": "rises / nullif(distance, 0)"}, "eco_pst": {"pst": "standing / nullif(duration, 0)"},
    "eco_stops": {"stops": "stops", "mean_stop": "CASE WHEN stops > 0 THEN standing / stops END"}, "eco_brakes": {"brakes": "brakes", "brakes_per_km": "brakes / nullif(distance, 0)"},
    "eco_gear_shifts": {"gear_shifts": "gear_shifts", "shifts_per_km": "gear_shifts / nullif(distance, 0)"}, "eco_rpm": {"avg_rpm": "avg_rpm"},
    "eco_braking_distance": {"braking_distance": "CASE WHEN run_stops > 0 THEN braked / run_stops END"}, "eco_distance": {"distance": "distance", "duration": "duration"}, "eco_extrema": {"extrema": "extrema"},
}
WHOLE = {"stops", "brakes", "gear_shifts", "extrema"}


def eco(cols: dict[str, str]):
    def run(s: SparkSession, d: str) -> DataFrame:
        rows = T.indicators(B.trips8(s, d), tie="event_id")
        return rows.select("trip_id", *[F.col(c) if c in WHOLE else snap(F.col(c), 5).alias(c) for c in cols])

    return run


for _name, _cols in COLUMNS.items():
    query(_name, trips_sql(TRIPS8) + " SELECT CAST(trip_id AS BIGINT) AS trip_id, " + ", ".join(x if c in WHOLE else f"round({x}, 5) AS {c}" for c, x in _cols.items()) + " FROM g")(eco(_cols))

TRAPEZOID = f"""WITH {TRIPS8}, a AS (SELECT *, lag(v) OVER w AS v0, t - lag(t) OVER w AS dt FROM trips WINDOW w AS (PARTITION BY trip_id ORDER BY t, event_id)),
  b AS (SELECT *, CASE WHEN dt > 0 THEN (v - v0) / dt END AS a FROM a), c AS (SELECT *, CASE WHEN a IS NOT NULL THEN v * greatest(a, 0) END AS p FROM b),
  d AS (SELECT *, (p + coalesce(lag(p) OVER (PARTITION BY trip_id ORDER BY t, event_id), v0 * greatest(a, 0))) / 2 AS q FROM c)
  SELECT CAST(trip_id AS BIGINT) AS trip_id, round(sum(q * dt) FILTER (dt > 0) / sum(dt), 5) AS rpa, round(sum((v + v0) / 2 * dt / 3600), 5) AS distance FROM d GROUP BY trip_id"""
query("eco_rpa_trapezoid", TRAPEZOID)(lambda s, d: T.indicators(B.trips8(s, d), "trapezoid", tie="event_id").select("trip_id", snap(F.col("rpa"), 5).alias("rpa"), snap(F.col("distance"), 5).alias("distance")))
query("eco_users", trips_sql(TRIPS) + " SELECT CAST(trip_id AS BIGINT) AS trip_id, n, round(rises / nullif(duration, 0), 5) AS pke, round(standing / nullif(duration, 0), 5) AS pst, round(power / nullif(duration, 0), 5) AS rpa FROM g")(
    lambda s, d: T.indicators(B.trips(s, d), tie="event_id").select("trip_id", "n", *[snap(F.col(c), 5).alias(c) for c in ("pke", "pst", "rpa")]))

STYLED = "x AS (SELECT trip_id % 2 AS driver, ['normal', 'nervous', 'economical', 'assisted'][1 + (trip_id // 2) % 4] AS style, power / duration AS rpa, rises / duration AS pke, standing / duration AS pst FROM g)"


@query("eco_styles", trips_sql(TRIPS8) + f", {STYLED}, y AS (SELECT driver, style, avg(rpa) AS rpa, avg(pke) AS pke, avg(pst) AS pst FROM x GROUP BY ALL) SELECT CAST(driver AS BIGINT) AS driver, style, " + ", ".join(
    f"round({c}, 5) AS {c}, round({c} - max({c}) FILTER (style = 'normal') OVER (PARTITION BY driver), 5) AS {c}_diff" for c in ("rpa", "pke", "pst")) + " FROM y")
def eco_styles(s: SparkSession, d: str) -> DataFrame:
    rows = T.compare_styles(T.indicators(B.trips8(s, d), tie="event_id"), B.styles8(s), ["rpa", "pke", "pst"])
    return rows.select("driver", "style", *[snap(F.col(f"{c}{x}"), 5).alias(f"{c}{x}") for c in ("rpa", "pke", "pst") for x in ("", "_diff")])


@query("eco_corr", trips_sql(TRIPS) + ", k AS (SELECT power / nullif(duration, 0) AS rpa, rises / nullif(duration, 0) AS pke, standing / nullif(duration, 0) AS pst, avg_rpm FROM g) SELECT 'rpa' AS x, 'pke' AS y, round(corr(rpa, pke), 5) AS r FROM k UNION ALL SELECT 'rpa', 'avg_rpm', round(corr(rpa, avg_rpm), 5) FROM k UNION ALL SELECT 'pke', 'avg_rpm', round(corr(pke, avg_rpm), 5) FROM k")
def eco_corr(s: SparkSession, d: str) -> DataFrame:
    return T.correlation(T.indicators(B.trips(s, d), tie="event_id"), ["rpa", "pke", "avg_rpm"]).withColumn("r", snap(F.col("r"), 5))


query("eco_pca")(lambda s, d: T.principal_components(T.indicators(B.trips(s, d), tie="event_id"), ["rpa", "pke", "pst", "avg_speed", "avg_rpm"]))
query("q4_pke_trips", f"WITH {TRIPS}, o AS (SELECT *, row_number() OVER (PARTITION BY trip_id ORDER BY t, event_id) - 1 AS idx FROM trips), p AS (SELECT *, lag(v) OVER w AS p, lag(v, 2) OVER w AS p2 FROM o WINDOW w AS (PARTITION BY trip_id ORDER BY idx)) SELECT CAST(trip_id AS VARCHAR) AS series_id, CAST(idx AS BIGINT) AS idx, round(v * v - p * p, 4) AS v FROM p WHERE v - p2 > 0")(
    lambda s, d: trips_q4(s, d))


def trips_q4(s: SparkSession, d: str) -> DataFrame:
    from pyspark.sql import Window

    from .windows import q4

    rows = B.trips(s, d)
    idx = F.row_number().over(Window.partitionBy("trip_id").orderBy("t", "event_id")).cast("long") - 1
    a = SeriesFrame(rows.select(F.col("trip_id").cast("string").alias("series_id"), idx.alias("idx"), "v"), B.POSITIONS)
    return q4(a, False).select("series_id", "idx", snap(F.col("v"), 4).alias("v"))


