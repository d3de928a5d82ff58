"""Queries on distances, reductions, fits, functions for SQL, and the batch twins of the streaming operators."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import udfs as U
from ..functions import vectors as V
from ..operators import algebra as A
from ..series import SeriesFrame, result, snap
from ..session import scratch
from ..sources import base as B
from ..streaming import stream as S
from .text import BY_TYPE, HOURLY, TWO_TYPES, frame, registry, series

QUERIES, ORACLES, query = registry()


def two(s: SparkSession, d: str) -> tuple[SeriesFrame, SeriesFrame]:
    return B.of_type(s, d, "click"), B.of_type(s, d, "view")


PAIR = f"WITH {TWO_TYPES} SELECT 'e' AS series_id, round({{}}, 5) AS distance FROM e1 JOIN e2 USING (idx)"
for _name, _p, _sql in (("dist_euclidean", 2.0, "sqrt(sum(pow(e1.v - e2.v, 2)))"), ("dist_l1", 1.0, "sum(abs(e1.v - e2.v))"), ("dist_chebyshev", float("inf"), "max(abs(e1.v - e2.v))")):
    query(_name, PAIR.format(_sql))(lambda s, d, p=_p: V.lp(*two(s, d), p).select("series_id", snap(F.col("distance"), 5).alias("distance")))

#: Every row whose id is divisible by 20 asks, against all rows.
QUERY_IDS = "vec_id % 20 = 0"


@query("knn_embeddings", f"""SELECT query_id, vec_id, distance, CAST(k AS INTEGER) AS rank FROM (SELECT q.vec_id AS query_id, v.vec_id, round(sqrt(list_sum(list_transform(list_zip(v.embedding, q.embedding), lambda z: pow(CAST(z[1] AS DOUBLE) - CAST(z[2] AS DOUBLE), 2)))), 6) AS distance,
  row_number() OVER (PARTITION BY q.vec_id ORDER BY round(sqrt(list_sum(list_transform(list_zip(v.embedding, q.embedding), lambda z: pow(CAST(z[1] AS DOUBLE) - CAST(z[2] AS DOUBLE), 2)))), 6), v.vec_id) AS k
  FROM embeddings v JOIN (SELECT * FROM embeddings WHERE {QUERY_IDS}) q ON v.vec_id <> q.vec_id) WHERE k <= 5""")
def knn_embeddings(s: SparkSession, d: str) -> DataFrame:
    v = B.read_table(s, d, "embeddings", ["vec_id", "embedding"])
    return V.knn(v.where(QUERY_IDS), v, 5)


@query("dtw_embeddings")
def dtw_embeddings(s: SparkSession, d: str) -> DataFrame:
    v = B.read_table(s, d, "embeddings", ["vec_id", "embedding"])
    return V.dtw_knn(v.where(QUERY_IDS), v, 5, 8)


query("paa_8", series(HOURLY, "SELECT series_id, idx // 8 AS idx, avg(v) AS v FROM hourly GROUP BY ALL"))(lambda s, d: result(V.paa(B.hourly(s, d), 8)))
query("haar_1", f"WITH {HOURLY} SELECT series_id, CAST(idx // 2 AS BIGINT) AS idx, round((max(v) FILTER (idx % 2 = 0) + max(v) FILTER (idx % 2 = 1)) / sqrt(2), 5) AS smooth, round((max(v) FILTER (idx % 2 = 0) - max(v) FILTER (idx % 2 = 1)) / sqrt(2), 5) AS detail FROM hourly GROUP BY ALL HAVING count(*) = 2")(
    lambda s, d: V.haar(B.hourly(s, d)).select("series_id", "idx", snap(F.col("smooth"), 5).alias("smooth"), snap(F.col("detail"), 5).alias("detail")))
HAAR = " UNION ALL ".join(f"SELECT series_id, {l} AS level, CAST(idx // {1 << l} AS BIGINT) AS idx, round(sum(v) / sqrt({1 << l}), 5) AS smooth, round(sum(CASE WHEN (idx // {1 << (l - 1)}) % 2 = 0 THEN v ELSE -v END) / sqrt({1 << l}), 5) AS detail FROM hourly GROUP BY ALL HAVING count(*) = {1 << l}" for l in (1, 2, 3, 4))
query("haar_levels_4", f"WITH {HOURLY} {HAAR}")(
    lambda s, d: V.haar_levels(B.hourly(s, d), 4).select("series_id", "level", "idx", snap(F.col("smooth"), 5).alias("smooth"), snap(F.col("detail"), 5).alias("detail")))
query("dft_k", f"WITH {HOURLY} SELECT series_id, CAST(f AS INTEGER) AS freq, round(sum(v * cos(2 * pi() / 720 * f * idx)), 3) AS re, round(sum(-v * sin(2 * pi() / 720 * f * idx)), 3) AS im FROM hourly, range(4) r(f) GROUP BY ALL")(
    lambda s, d: V.dft(B.hourly(s, d), 4, 720).select("series_id", "freq", snap(F.col("re"), 3).alias("re"), snap(F.col("im"), 3).alias("im")))
query("pla_pieces")(lambda s, d: V.pla(B.hourly_by_type(s, d), 20.0))
query("svd_embeddings")(lambda s, d: V.svd(B.read_table(s, d, "embeddings", ["vec_id", "embedding"]), 3).select("vec_id", "reduced"))
query("ar1_fit", f"WITH {BY_TYPE}, p AS (SELECT *, max(v) OVER (PARTITION BY series_id ORDER BY idx RANGE BETWEEN 1 PRECEDING AND 1 PRECEDING) AS p FROM hbt) SELECT series_id, round(regr_slope(v, p), 6) AS phi, round(regr_intercept(v, p), 4) AS c FROM p WHERE p IS NOT NULL GROUP BY ALL")(
    lambda s, d: V.ar1_fit(B.hourly_by_type(s, d)).select("series_id", snap(F.col("phi"), 6).alias("phi"), snap(F.col("c"), 4).alias("c")))
query("ar_forecast")(lambda s, d: (lambda a: V.ar_forecast(a, V.ar_fit(a, 3), 5))(B.hourly_by_type(s, d)))
query("trend_regr", f"WITH {BY_TYPE} SELECT series_id, round(regr_slope(v, idx), 7) AS slope, round(regr_intercept(v, idx), 4) AS intercept, round(regr_r2(v, idx), 7) AS r2 FROM hbt GROUP BY ALL")(
    lambda s, d: V.trend(B.hourly_by_type(s, d)).select("series_id", snap(F.col("slope"), 7).alias("slope"), snap(F.col("intercept"), 4).alias("intercept"), snap(F.col("r2"), 7).alias("r2")))
query("series_summary", f"WITH {BY_TYPE} SELECT series_id, count(v) AS n, round(avg(v), 4) AS mean, round(quantile_cont(v, 0.5), 4) AS p50 FROM hbt GROUP BY ALL")(
    lambda s, d: V.summary(B.hourly_by_type(s, d)).select("series_id", "n", snap(F.col("mean"), 4).alias("mean"), snap(F.col("p50"), 4).alias("p50")))

# ---- functions for SQL and Python ---------------------------------------------------------------------------------------

query("udf_scalar", series(HOURLY, "SELECT series_id, idx, least(greatest(v, 0), 100) / 2 AS v FROM hourly"))(lambda s, d: result(A.project(B.hourly(s, d), U.clip_scale)))


@query("udf_grouped", f"WITH {BY_TYPE} SELECT series_id, round(max(v) - min(v), 4) AS spread FROM hbt GROUP BY ALL")
def udf_grouped(s: SparkSession, d: str) -> DataFrame:
    def one(pdf):
        return pdf.groupby("series_id")["v"].agg(lambda v: v.max() - v.min()).rename("spread").reset_index()

    return B.hourly_by_type(s, d).df.groupBy("series_id").applyInPandas(one, "series_id string, spread double").select("series_id", snap(F.col("spread"), 4).alias("spread"))


@query("udtf_calendar", "SELECT CAST(i AS BIGINT) AS idx, TIMESTAMP '2024-01-01' + to_hours(CAST(i AS BIGINT)) AS t FROM range(48) r(i)")
def udtf_calendar(s: SparkSession, d: str) -> DataFrame:
    U.register(s)
    return s.sql("SELECT * FROM calendar_range('2024-01-01', 3600, 48)")


@query("udtf_segments", "SELECT i AS idx, CAST(unnest(range(greatest(0, (i - 4) // 16 - CASE WHEN i < 4 THEN 1 ELSE 0 END), (i + 8) // 16 + 1)) AS BIGINT) AS seg FROM range(64) r(i)")
def udtf_segments(s: SparkSession, d: str) -> DataFrame:
    U.register(s)
    s.range(64).createOrReplaceTempView("cs_range")
    return s.sql("SELECT id AS idx, seg FROM cs_range, LATERAL segment_ids(id, 16, 8, 4)")


ARRAYS = f"WITH {HOURLY}, dense AS (SELECT 'hourly' AS series_id, row_number() OVER (ORDER BY idx) - 1 AS idx, v FROM hourly)"


@query("sql_function_mavg", f"{ARRAYS} SELECT CAST(idx AS INTEGER) AS k, round(avg(v) OVER {frame(6)}, 5) AS m, round(avg(v) OVER {frame(3)} - avg(v) OVER {frame(6)}, 5) AS c FROM dense")
def sql_function_mavg(s: SparkSession, d: str) -> DataFrame:
    U.register(s)
    packed = B.hourly(s, d).df.groupBy("series_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("idx", "v"))), lambda x: x["v"]).alias("vals"))
    packed.createOrReplaceTempView("cs_packed")
    rows = s.sql("SELECT ts_mavg(vals, 6) AS m, ts_macd(vals, 3, 6) AS c FROM cs_packed").select(F.posexplode(F.arrays_zip("m", "c")).alias("k", "z"))
    return rows.select("k", snap(F.col("z.m"), 5).alias("m"), snap(F.col("z.c"), 5).alias("c"))


# ---- streams: each runs over all files there are, and must equal its batch twin -------------------------------------------

HOUR = "SELECT {} AS start, event_type, count(*) AS n, round(sum(value), 3) AS total FROM {} GROUP BY ALL"


def stamped(df: DataFrame) -> DataFrame:
    return df.withColumn("start", F.col("start").cast("timestamp_ntz")).withColumn("total", snap(F.col("total"), 3))


def streamed(op, mode: str = "complete"):
    def run(s: SparkSession, d: str) -> DataFrame:
        name = f"cs_{uuid.uuid4().hex[:12]}"
        return stamped(S.run_once(op(S.read_events(s, d)), name, mode, scratch(s, "stream")))

    return run


query("stream_tumbling", HOUR.format("date_trunc('hour', ts)", "events"))(streamed(S.tumbling))
query("stream_sliding", HOUR.format("date_trunc('hour', ts) - to_hours(CAST(k AS BIGINT))", "events, range(2) r(k)"))(streamed(S.sliding))
query("stream_session", "WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS new FROM events), k AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM g) SELECT user_id, min(ts) AS start, count(*) AS n, round(sum(value), 3) AS total FROM k GROUP BY user_id, s")(
    streamed(S.sessions))
query("batch_tumbling", HOUR.format("date_trunc('hour', ts)", "events"))(lambda s, d: stamped(S.tumbling(B.read_table(s, d, "events"))))


@query("stream_recursive", """WITH RECURSIVE o AS (SELECT user_id, event_id, value, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM events),
  y AS (SELECT user_id, event_id, k, value AS y FROM o WHERE k = 1 UNION ALL SELECT o.user_id, o.event_id, o.k, 0.1 * o.value + 0.9 * y.y FROM y JOIN o ON o.user_id = y.user_id AND o.k = y.k + 1)
  SELECT user_id, event_id, round(y, 4) AS y FROM y""")
def stream_recursive(s: SparkSession, d: str) -> DataFrame:
    name = f"cs_{uuid.uuid4().hex[:12]}"
    return S.run_once(S.recursive_average(S.read_events(s, d)), name, "append", scratch(s, "stream")).select("user_id", "event_id", snap(F.col("y"), 4).alias("y"))


@query("stream_last_w", "SELECT user_id, event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 4 PRECEDING), 4) AS y FROM events")
def stream_last_w(s: SparkSession, d: str) -> DataFrame:
    name = f"cs_{uuid.uuid4().hex[:12]}"
    return S.run_once(S.last_w_average(S.read_events(s, d), 5), name, "append", scratch(s, "stream")).select("user_id", "event_id", snap(F.col("y"), 4).alias("y"))


@query("stream_dedup", "SELECT event_id, user_id FROM events")
def stream_dedup(s: SparkSession, d: str) -> DataFrame:
    """Every event arrives twice."""
    twice = S.read_events(s, d).withColumn("_copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("_copy")
    return S.run_once(S.deduplicated(twice), f"cs_{uuid.uuid4().hex[:12]}", "append", scratch(s, "stream")).select("event_id", "user_id")


@query("stream_static_join", "SELECT event_id, c_name FROM events LEFT JOIN customer ON user_id = c_custkey")
def stream_static_join(s: SparkSession, d: str) -> DataFrame:
    who = B.read_table(s, d, "customer", ["c_custkey", "c_name"]).withColumnRenamed("c_custkey", "user_id")
    return S.run_once(S.with_dimension(S.read_events(s, d), who, "user_id"), f"cs_{uuid.uuid4().hex[:12]}", "append", scratch(s, "stream")).select("event_id", "c_name")


@query("stream_append", series(BY_TYPE, "SELECT * FROM hbt"))
def stream_append(s: SparkSession, d: str) -> DataFrame:
    path = scratch(s, "appended")
    S.append_series(S.read_events(s, d), B.HOURS, path, scratch(s, "stream"), 256).awaitTermination()
    return result(S.read_appended(s, path, B.HOURS))


@query("stream_interval_join", "SELECT p.user_id, p.event_id AS l_id, v.event_id AS r_id FROM events p JOIN events v ON p.user_id = v.user_id AND v.ts <= p.ts AND v.ts >= p.ts - INTERVAL 6 HOUR WHERE p.event_type = 'purchase' AND v.event_type = 'view'")
def stream_interval_join(s: SparkSession, d: str) -> DataFrame:
    e = S.read_events(s, d)
    name = f"cs_{uuid.uuid4().hex[:12]}"
    return S.run_once(S.interval_join(e.where("event_type = 'purchase'"), e.where("event_type = 'view'")), name, "append", scratch(s, "stream"))


