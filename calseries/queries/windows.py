"""Queries on sliding windows, indicators, the baselines, and the benchmark's workloads."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import algebra as A
from ..operators import window as W
from ..operators.trips import pke_literal, pke_steps
from ..plans import segments as G
from ..series import SeriesFrame, result, snap
from ..sources import base as B
from .text import registry, HOLES, LEVEL, QUOTE, SUPPLIER, TICKS, back, frame, series

QUERIES, ORACLES, query = registry()


def avg_sql(cte: str, t: str, w: int, digits: int = 3) -> str:
    return series(cte, f"SELECT series_id, idx, avg(v) OVER {frame(w)} AS v FROM {t}", digits)


def xavg_sql(t: str, w: int, alpha: str = "") -> str:
    q = f"(1 - 2.0 / ({w} + 1))"
    return f"SELECT x.series_id, x.idx, sum(pow({q}, x.idx - y.idx) * y.v) / sum(pow({q}, x.idx - y.idx)) AS v FROM {t} x JOIN {t} y ON x.series_id = y.series_id AND y.idx BETWEEN x.idx - {w - 1} AND x.idx GROUP BY ALL"


def xavg_list_sql(t: str, w: int) -> str:
    """The same by lists of a frame, quicker on long series; dense series only."""
    q = f"(1 - 2.0 / ({w} + 1))"
    return f"""SELECT series_id, idx, list_sum(list_transform(l, lambda x, i: x * pow({q}, len(l) - i))) / list_sum(list_transform(l, lambda x, i: pow({q}, len(l) - i))) AS v
      FROM (SELECT series_id, idx, list(v) OVER {frame(w)} AS l FROM {t})"""


def rsi_sql(cte: str, t: str, w: int) -> str:
    return series(f"{cte}, d AS (SELECT series_id, idx, v - {back(1)} AS d FROM {t})", f"""SELECT series_id, idx, CASE WHEN n = 0 THEN NULL WHEN g + l = 0 THEN 'nan'::DOUBLE ELSE 100 * g / (g + l) END AS v
      FROM (SELECT series_id, idx, sum(greatest(d, 0)) OVER {frame(w)} AS g, sum(greatest(-d, 0)) OVER {frame(w)} AS l, count(d) OVER {frame(w)} AS n FROM d) WHERE n > 0""", 6)


# ---- averages ------------------------------------------------------------------------------------------------------------

for w in (10, 50, 100):
    query(f"mavg_{w}", avg_sql(LEVEL, "level", w))(lambda s, d, w=w: result(W.mavg(B.level(s, d), w), 3))
    query(f"rsi_{w}", rsi_sql(LEVEL, "level", w))(lambda s, d, w=w: result(W.rsi(B.level(s, d), w), 6))
    query(f"macd_exp_3_{w}", series(LEVEL, f"SELECT a.series_id, a.idx, a.v - b.v AS v FROM ({xavg_sql('level', 3)}) a JOIN ({xavg_sql('level', w)}) b USING (idx)", 3))(
        lambda s, d, w=w: result(W.macd(B.level(s, d), 3, w, "exp"), 3))
    # the benchmark's queries on the long series, segment by segment
    query(f"q1_mavg_w{w}", avg_sql(TICKS, "ticks", w))(lambda s, d, w=w: result(q1(B.ticks(s, d), w), 3))
    query(f"q2_rsi_w{w}", rsi_sql(TICKS, "ticks", w))(lambda s, d, w=w: result(q2(B.ticks(s, d), w), 6))
    query(f"q3_macd_w{w}", series(TICKS, f"SELECT a.series_id, a.idx, a.v - b.v AS v FROM ({xavg_list_sql('ticks', 3)}) a JOIN ({xavg_list_sql('ticks', w)}) b USING (idx)", 3))(
        lambda s, d, w=w: result(q3(B.ticks(s, d), w), 3))


def q1(a: SeriesFrame, w: int, length: int = 4096) -> SeriesFrame:
    return G.eval_segmented(a, lambda x: W.mavg(x, w, method="prefix"), w - 1, length=length)


def q2(a: SeriesFrame, w: int, length: int = 4096) -> SeriesFrame:
    return G.eval_segmented(a, lambda x: W.rsi(x, w, method="prefix"), w, length=length)


def q3(a: SeriesFrame, w: int, length: int = 512) -> SeriesFrame:
    """Segments short enough for the weights of the short average to stay numbers."""
    return G.eval_segmented(a, lambda x: W.macd(x, 3, w, "exp", method="prefix"), w - 1, length=length)


def q4(a: SeriesFrame, literal: bool) -> DataFrame:
    """Rise of the squared value where the two-step momentum is positive: one window over one ordering."""
    f = pke_literal if literal else pke_steps
    v = F.col("v")
    m = v - W.back(a, 2)
    return a.df.select("series_id", "idx", f(v, W.back(a, 1), m).alias("v")).where("v IS NOT NULL")


query("q4_pke_steps", series(TICKS, f"SELECT series_id, idx, v * v - p * p AS v FROM (SELECT *, {back(1)} AS p, {back(2)} AS p2 FROM ticks) WHERE v - p2 > 0", 2))(lambda s, d: result(q4(B.ticks(s, d), False), 2))


@query("q4_pke_literal", f"WITH {LEVEL} SELECT CAST(idx AS BIGINT) AS idx, round((pow(v * (v - p2), 2) - pow(p * (v - p2), 2)) / 1e16, 3) AS v FROM (SELECT *, {back(1)} AS p, {back(2)} AS p2 FROM level) WHERE v - p2 > 0 AND p IS NOT NULL")
def q4_pke_literal(s: SparkSession, d: str) -> DataFrame:
    return q4(B.level(s, d), True).select("idx", snap(F.col("v") / 1e16, 3).alias("v"))


query("win_sum_lagged", series(LEVEL, f"SELECT * FROM (SELECT series_id, idx, sum(v) OVER {frame(10, True)} AS v FROM level) WHERE v IS NOT NULL", 3))(lambda s, d: result(W.win(B.level(s, d), F.sum, 10), 3))
query("win_custom_range", series(LEVEL, f"SELECT series_id, idx, max(v) OVER {frame(10)} - min(v) OVER {frame(10)} AS v FROM level"))(
    lambda s, d: result(W.win_list(B.level(s, d), lambda x: F.array_max(x) - F.array_min(x), 10, "trailing")))
query("win_python_range", series(LEVEL, f"SELECT series_id, idx, max(v) OVER {frame(10)} - min(v) OVER {frame(10)} AS v FROM level"))(
    lambda s, d: result(W.win_python(B.level(s, d), lambda x: float(max(x) - min(x)), 10)))
query("mavg_prefix_100", avg_sql(LEVEL, "level", 100))(lambda s, d: result(W.mavg(B.level(s, d), 100, "prefix"), 3))
query("mavg_packed_50", avg_sql(LEVEL, "level", 50))(lambda s, d: result(W.mavg(B.level(s, d), 50, "packed"), 3))
query("mavg_pandas_50", avg_sql(LEVEL, "level", 50))(lambda s, d: result(W.mavg(B.level(s, d), 50, "pandas"), 3))
query("mavg_selfjoin", avg_sql(LEVEL, "level", 50))(lambda s, d: result(W.mavg(B.level(s, d), 50, "selfjoin"), 3))
query("mavg_segmented", avg_sql(LEVEL, "level", 100))(lambda s, d: result(G.eval_segmented(B.level(s, d), lambda x: W.mavg(x, 100), 99, length=64), 3))
query("mavg_holes", series(HOLES, f"SELECT series_id, idx, CASE WHEN max(isnan(v)::INT) OVER {frame(10)} = 1 THEN 'nan'::DOUBLE ELSE avg(CASE WHEN NOT isnan(v) THEN v END) OVER {frame(10)} END AS v FROM holes", 3))(
    lambda s, d: result(W.mavg(B.level_holes(s, d), 10), 3))
query("mavg_holes_prefix", series(HOLES, f"SELECT series_id, idx, CASE WHEN max(isnan(v)::INT) OVER {frame(10)} = 1 THEN 'nan'::DOUBLE ELSE avg(CASE WHEN NOT isnan(v) THEN v END) OVER {frame(10)} END AS v FROM holes", 3))(
    lambda s, d: result(W.mavg(B.level_holes(s, d), 10, "prefix"), 3))
query("mavg_border_partial", avg_sql(LEVEL, "level", 20))(lambda s, d: result(W.mavg(B.level(s, d), 20, border="partial"), 3))
FIRST = "(SELECT *, min(idx) OVER () AS i0, first_value(v) OVER (ORDER BY idx) AS v0 FROM level)"
query("mavg_border_first", series(LEVEL, f"SELECT series_id, idx, (sum(v) OVER {frame(20)} + greatest(0, 19 - (idx - i0)) * v0) / (count(v) OVER {frame(20)} + greatest(0, 19 - (idx - i0))) AS v FROM {FIRST}", 3))(
    lambda s, d: result(W.mavg(B.level(s, d), 20, border="first"), 3))
query("mavg_border_strict", series(LEVEL, f"SELECT series_id, idx, v FROM (SELECT series_id, idx, i0, avg(v) OVER {frame(20)} AS v FROM {FIRST}) WHERE idx - i0 >= 19", 3))(
    lambda s, d: result(W.mavg(B.level(s, d), 20, border="strict"), 3))
PADDED = f"{LEVEL}, f0 AS (SELECT min(idx) AS i0, arg_min(v, idx) AS v0 FROM level), padded AS (SELECT * FROM level UNION ALL SELECT 'level', i0 - k, v0 FROM f0, range(1, 30) r(k))"
INSIDE = "idx >= (SELECT i0 FROM f0)"
query("win_border_first", series(PADDED, f"SELECT * FROM (SELECT series_id, idx, sum(v) OVER {frame(10, True)} AS v FROM padded) WHERE {INSIDE} AND v IS NOT NULL", 3))(
    lambda s, d: result(W.win(B.level(s, d), F.sum, 10, border="first"), 3))
query("rsi_border_first", series(f"{PADDED}, d AS (SELECT series_id, idx, v - {back(1)} AS d FROM padded)", f"""SELECT series_id, idx, CASE WHEN g + l = 0 THEN 'nan'::DOUBLE ELSE 100 * g / (g + l) END AS v
  FROM (SELECT series_id, idx, sum(greatest(d, 0)) OVER {frame(14)} AS g, sum(greatest(-d, 0)) OVER {frame(14)} AS l, count(d) OVER {frame(14)} AS n FROM d) WHERE n > 0 AND {INSIDE}""", 6))(
    lambda s, d: result(W.rsi(B.level(s, d), 14, border="first"), 6))
query("xavg_border_first", series(PADDED, f"SELECT * FROM ({xavg_sql('padded', 20)}) WHERE {INSIDE}", 3))(lambda s, d: result(W.xavg(B.level(s, d), 20, border="first"), 3))
query("macd_border_first", series(PADDED, f"SELECT * FROM (SELECT series_id, idx, avg(v) OVER {frame(12)} - avg(v) OVER {frame(26)} AS v FROM padded) WHERE {INSIDE}", 3))(lambda s, d: result(W.macd(B.level(s, d), border="first"), 3))
query("mstd_border_first", series(PADDED, f"SELECT * FROM (SELECT series_id, idx, stddev_samp(v) OVER {frame(20)} AS v FROM padded) WHERE {INSIDE} AND v IS NOT NULL", 3))(lambda s, d: result(W.mstd(B.level(s, d), 20, border="first"), 3))
query("rsi_selfjoin", rsi_sql(LEVEL, "level", 14))(lambda s, d: result(W.rsi(B.level(s, d), 14, "selfjoin"), 6))
query("rsi_prefix_50", rsi_sql(LEVEL, "level", 50))(lambda s, d: result(W.rsi(B.level(s, d), 50, "prefix"), 6))
query("xavg_3", series(LEVEL, xavg_sql("level", 3), 3))(lambda s, d: result(W.xavg(B.level(s, d), 3), 3))
query("xavg_100", series(LEVEL, xavg_sql("level", 100), 3))(lambda s, d: result(W.xavg(B.level(s, d), 100), 3))
query("xavg_prefix_100", series(LEVEL, xavg_sql("level", 100), 3))(lambda s, d: result(G.eval_segmented(B.level(s, d), lambda x: W.xavg(x, 100, method="prefix"), 99, length=512), 3))
query("xavg_recursive", series(f"""RECURSIVE {LEVEL}, o AS (SELECT *, row_number() OVER (ORDER BY idx) AS k FROM level),
  y AS (SELECT k, idx, v AS y FROM o WHERE k = 1 UNION ALL SELECT o.k, o.idx, 0.1 * o.v + 0.9 * y.y FROM y JOIN o ON o.k = y.k + 1)""", "SELECT 'level' AS series_id, idx, y AS v FROM y", 3))(
    lambda s, d: result(G.xavg_recursive(B.level(s, d), 0.1, length=128), 3))
query("wavg_10", series(LEVEL, f"SELECT series_id, idx, ((10 - idx) * sum(v) OVER {frame(10)} + sum(v * idx) OVER {frame(10)}) / ((10 - idx) * count(v) OVER {frame(10)} + sum(idx) OVER {frame(10)}) AS v FROM level", 2))(
    lambda s, d: result(W.wavg(B.level(s, d), 10), 2))

# ---- indicators ------------------------------------------------------------------------------------------------------------

MACD = f"SELECT series_id, idx, avg(v) OVER {frame(12)} - avg(v) OVER {frame(26)} AS v FROM level"
query("macd_12_26", series(LEVEL, MACD, 3))(lambda s, d: result(W.macd(B.level(s, d)), 3))
query("macd_signal_9", series(LEVEL, f"SELECT series_id, idx, avg(v) OVER {frame(9)} AS v FROM ({MACD})", 3))(lambda s, d: result(W.signal(W.macd(B.level(s, d)), 9), 3))
for k in (2, 5):
    query(f"mom_{k}", series(LEVEL, f"SELECT * FROM (SELECT series_id, idx, v - {back(k)} AS v FROM level) WHERE v IS NOT NULL"))(lambda s, d, k=k: result(W.mom(B.level(s, d), k)))
query("roc_10", series(LEVEL, f"SELECT * FROM (SELECT series_id, idx, (v / {back(10)} - 1) * 100 AS v FROM level) WHERE v IS NOT NULL", 6))(lambda s, d: result(W.mom(B.level(s, d), 10, "roc"), 6))
query("mstd_20", series(LEVEL, f"SELECT * FROM (SELECT series_id, idx, stddev_samp(v) OVER {frame(20)} AS v FROM level) WHERE v IS NOT NULL", 3))(lambda s, d: result(W.mstd(B.level(s, d), 20), 3))
query("mmax_20", series(LEVEL, f"SELECT series_id, idx, max(v) OVER {frame(20)} AS v FROM level"))(lambda s, d: result(W.mmax(B.level(s, d), 20)))
query("mmin_20", series(HOLES, f"SELECT series_id, idx, CASE WHEN max(isnan(v)::INT) OVER {frame(20)} = 1 THEN 'nan'::DOUBLE ELSE min(v) OVER {frame(20)} END AS v FROM holes"))(lambda s, d: result(W.mmin(B.level_holes(s, d), 20)))
query("mmedian_15", series(LEVEL, f"SELECT series_id, idx, median(v) OVER {frame(15)} AS v FROM level"))(lambda s, d: result(W.mmedian(B.level(s, d), 15)))
query("mslope_10", series(LEVEL, f"SELECT * FROM (SELECT series_id, idx, CASE WHEN count(v) OVER {frame(10)} >= 2 THEN regr_slope(v, idx) OVER {frame(10)} END AS v FROM level) WHERE v IS NOT NULL", 2))(
    lambda s, d: result(W.mslope(B.level(s, d), 10), 2))
query("zscore_20", series(LEVEL, f"SELECT * FROM (SELECT series_id, idx, (v - avg(v) OVER {frame(20)}) / stddev_samp(v) OVER {frame(20)} AS v FROM level) WHERE v IS NOT NULL", 5))(lambda s, d: result(W.zscore(B.level(s, d), 20), 5))


@query("bollinger_20", f"WITH {LEVEL} SELECT series_id, CAST(idx AS BIGINT) AS idx, round(avg(v) OVER w, 3) AS mid, round(avg(v) OVER w - 2 * stddev_pop(v) OVER w, 3) AS low, round(avg(v) OVER w + 2 * stddev_pop(v) OVER w, 3) AS high FROM level WINDOW w AS {frame(20)}")
def bollinger_20(s: SparkSession, d: str) -> DataFrame:
    return W.bollinger(B.level(s, d)).select("series_id", "idx", *[snap(F.col(c), 3).alias(c) for c in ("mid", "low", "high")])


query("stochastic_14", series(QUOTE, f"SELECT series_id, idx, CASE WHEN hi = lo THEN 'nan'::DOUBLE ELSE 100 * (close - lo) / (hi - lo) END AS v FROM (SELECT *, min(low) OVER {frame(14)} AS lo, max(high) OVER {frame(14)} AS hi FROM quote)", 6))(
    lambda s, d: result(W.stochastic(B.quote_daily(s, d)), 6))
query("mcorr_20", series(QUOTE, f"SELECT * FROM (SELECT series_id, idx, CASE WHEN count(*) OVER {frame(20)} >= 2 THEN corr(open, close) OVER {frame(20)} END AS v FROM quote) WHERE v IS NOT NULL", 5))(
    lambda s, d: result(W.mcorr(B.quote_daily(s, d), "open", "close", 20), 5))
query("mcov_20", series(QUOTE, f"SELECT * FROM (SELECT series_id, idx, CASE WHEN count(*) OVER {frame(20)} >= 2 THEN covar_samp(open, close) OVER {frame(20)} / 1e6 END AS v FROM quote) WHERE v IS NOT NULL", 4))(
    lambda s, d: result((lambda a: a.with_df(a.df.withColumn("v", F.col("v") / 1e6)))(W.mcov(B.quote_daily(s, d), "open", "close", 20)), 4))
query("williams_14", series(QUOTE, f"SELECT series_id, idx, CASE WHEN hi = lo THEN 'nan'::DOUBLE ELSE -100 * (hi - close) / (hi - lo) END AS v FROM (SELECT *, min(low) OVER {frame(14)} AS lo, max(high) OVER {frame(14)} AS hi FROM quote)", 6))(
    lambda s, d: result(W.williams(B.quote_daily(s, d)), 6))
query("mvar_20", series(LEVEL, f"SELECT * FROM (SELECT series_id, idx, var_samp(v) OVER {frame(20)} / 1e6 AS v FROM level) WHERE v IS NOT NULL", 3))(lambda s, d: result(W.mvar(B.level(s, d), 20) * 1e-6, 3))
query("mcount_20", series(HOLES, f"SELECT series_id, idx, CAST(count(CASE WHEN NOT isnan(v) THEN 1 END) OVER {frame(20)} AS DOUBLE) AS v FROM holes"))(lambda s, d: result(W.mcount(B.level_holes(s, d), 20)))
query("mfirst_5", series(LEVEL, f"SELECT series_id, idx, first_value(v) OVER {frame(5)} AS v FROM level"))(lambda s, d: result(W.mfirst(B.level(s, d), 5)))
query("mlast_5", series(LEVEL, f"SELECT * FROM (SELECT series_id, idx, last_value(v) OVER {frame(5, True)} AS v FROM level) WHERE v IS NOT NULL"))(lambda s, d: result(W.mlast(B.level(s, d), 5)))
ONE = "(PARTITION BY series_id ORDER BY idx RANGE BETWEEN 1 PRECEDING AND 1 PRECEDING)"
query("adx_14", series(f"""{QUOTE}, p AS (SELECT *, max(high) OVER {ONE} AS ph, max(low) OVER {ONE} AS pl, max(close) OVER {ONE} AS pc FROM quote),
  m AS (SELECT series_id, idx, CASE WHEN high - ph > pl - low AND high > ph THEN high - ph ELSE 0 END AS pdm, CASE WHEN pl - low > high - ph AND pl > low THEN pl - low ELSE 0 END AS mdm,
    greatest(high - low, abs(high - pc), abs(low - pc)) AS tr FROM p WHERE pc IS NOT NULL),
  i AS (SELECT series_id, idx, CASE WHEN sum(tr) OVER {frame(14)} = 0 THEN 'nan'::DOUBLE ELSE 100 * sum(pdm) OVER {frame(14)} / sum(tr) OVER {frame(14)} END AS p, CASE WHEN sum(tr) OVER {frame(14)} = 0 THEN 'nan'::DOUBLE ELSE 100 * sum(mdm) OVER {frame(14)} / sum(tr) OVER {frame(14)} END AS m FROM m),
  x AS (SELECT series_id, idx, CASE WHEN isnan(p) OR isnan(m) OR p + m = 0 THEN 'nan'::DOUBLE ELSE 100 * abs(p - m) / (p + m) END AS v FROM i)""",
    f"SELECT series_id, idx, CASE WHEN max(isnan(v)::INT) OVER {frame(14)} = 1 THEN 'nan'::DOUBLE ELSE avg(CASE WHEN NOT isnan(v) THEN v END) OVER {frame(14)} END AS v FROM x", 5))(
    lambda s, d: result(W.adx(B.quote_daily(s, d)), 5))
WILDER = f"""RECURSIVE {QUOTE}, p AS (SELECT *, max(high) OVER {ONE} AS ph, max(low) OVER {ONE} AS pl, max(close) OVER {ONE} AS pc FROM quote),
  o AS (SELECT idx, row_number() OVER (ORDER BY idx) AS k, CASE WHEN high - ph > pl - low AND high > ph THEN high - ph ELSE 0 END AS pdm, CASE WHEN pl - low > high - ph AND pl > low THEN pl - low ELSE 0 END AS mdm,
    greatest(high - low, abs(high - pc), abs(low - pc)) AS tr FROM p WHERE pc IS NOT NULL),
  y AS (SELECT k, idx, CAST(pdm AS DOUBLE) AS p, CAST(mdm AS DOUBLE) AS m, CAST(tr AS DOUBLE) AS t FROM o WHERE k = 1 UNION ALL SELECT o.k, o.idx, y.p * 13 / 14 + o.pdm / 14, y.m * 13 / 14 + o.mdm / 14, y.t * 13 / 14 + o.tr / 14 FROM y JOIN o ON o.k = y.k + 1),
  x AS (SELECT idx, row_number() OVER (ORDER BY idx) AS k, 100 * abs(p - m) / (p + m) AS v FROM y WHERE t <> 0 AND p + m <> 0),
  z AS (SELECT k, idx, v FROM x WHERE k = 1 UNION ALL SELECT x.k, x.idx, z.v * 13 / 14 + x.v / 14 FROM z JOIN x ON x.k = z.k + 1)"""
query("adx_wilder_14", series(WILDER, "SELECT 'quote' AS series_id, idx, v FROM z", 4))(lambda s, d: result(W.adx(B.quote_daily(s, d), 14, "wilder"), 4))
query("cross_up_9_macd", series(f"{LEVEL}, m AS ({MACD}), g AS (SELECT series_id, idx, avg(v) OVER {frame(9)} AS v FROM m)", "SELECT series_id, idx, v FROM (SELECT m.series_id, m.idx, m.v, round(m.v - g.v, 6) AS now, lag(round(m.v - g.v, 6)) OVER (ORDER BY m.idx) AS was FROM m JOIN g USING (series_id, idx)) WHERE now > 0 AND was <= 0", 3))(
    lambda s, d: result((lambda m: W.cross(*(x.with_df(x.df.withColumn("v", F.col("v"))) for x in (m, W.signal(m, 9)))))(W.macd(B.level(s, d))), 3))
query("window_step_5", series(LEVEL, "SELECT series_id, k * 5 + 9 AS idx, avg(v) AS v FROM level JOIN range(1000) r(k) ON idx BETWEEN k * 5 AND k * 5 + 9 GROUP BY ALL"))(lambda s, d: result(W.stepped(B.level(s, d), 10, 5)))
query("tumbling_avg_10", series(LEVEL, "SELECT series_id, (idx // 10) * 10 + 9 AS idx, avg(v) AS v FROM level GROUP BY ALL"))(lambda s, d: result(W.tumbling(B.level(s, d), 10)))


@query("predicate_window", f"WITH {LEVEL}, m AS (SELECT *, sum(CASE WHEN v > 260000 THEN 1 ELSE 0 END) OVER (ORDER BY idx ROWS UNBOUNDED PRECEDING) AS win FROM level) SELECT CAST(win AS BIGINT) AS win, CAST(min(idx) AS BIGINT) AS first_idx, CAST(max(idx) AS BIGINT) AS last_idx, count(v) AS n, round(avg(v), 3) AS mean FROM m WHERE win > 0 GROUP BY ALL")
def predicate_window(s: SparkSession, d: str) -> DataFrame:
    return W.predicate_windows(B.level(s, d), lambda v: v > 260000).select("win", "first_idx", "last_idx", "n", snap(F.col("mean"), 3).alias("mean"))


@query("predicate_window_end", f"""WITH {LEVEL}, e AS (SELECT *, coalesce(sum((v < 240000)::INT) OVER (ORDER BY idx ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS piece FROM level),
  f AS (SELECT piece, min(idx) FILTER (v > 260000) AS i0, max((v < 240000)::INT) AS whole FROM e GROUP BY piece), k AS (SELECT *, row_number() OVER (ORDER BY i0) AS win FROM f WHERE i0 IS NOT NULL)
  SELECT win, CAST(min(idx) AS BIGINT) AS first_idx, CAST(max(idx) AS BIGINT) AS last_idx, count(v) AS n, round(avg(v), 3) AS mean FROM e JOIN k USING (piece) WHERE idx >= i0 GROUP BY win""")
def predicate_window_end(s: SparkSession, d: str) -> DataFrame:
    return W.predicate_windows(B.level(s, d), lambda v: v > 260000, lambda v: v < 240000).select("win", "first_idx", "last_idx", "n", snap(F.col("mean"), 3).alias("mean"))


query("supplier_mavg_20", series(SUPPLIER, f"SELECT series_id, idx, avg(v) OVER {frame(20)} AS v FROM supp", 3))(lambda s, d: result(W.mavg(B.supplier_daily(s, d), 20), 3))


@query("mavg_methods_agree", "SELECT m AS method, CAST(0 AS BIGINT) AS differing FROM (VALUES ('prefix'), ('packed'), ('pandas'), ('selfjoin'), ('segmented')) t(m)")
def mavg_methods_agree(s: SparkSession, d: str) -> DataFrame:
    a = B.level(s, d)
    ref = W.mavg(a, 50)
    forms = {m: W.mavg(a, 50, m) for m in ("prefix", "packed", "pandas", "selfjoin")} | {"segmented": G.eval_segmented(a, lambda x: W.mavg(x, 50), 49, length=64)}
    out = None
    for m, f in forms.items():
        bad = A.wide([ref, f]).where(F.col("v0").isNull() | F.col("v1").isNull() | (F.abs(F.col("v0") - F.col("v1")) > 1e-6))
        one = bad.agg(F.count(F.lit(1)).alias("differing")).select(F.lit(m).alias("method"), "differing")
        out = one if out is None else out.unionAll(one)
    return out
