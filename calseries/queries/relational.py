"""Queries on the operators around the series: scans, joins, aggregates, windows, sets, sub-queries, functions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, WindowSpec
from pyspark.sql import functions as F

from ..operators import joins as J
from ..operators import window as W
from ..plans import segments as G
from ..series import result, snap
from ..session import scratch
from ..sources import base as B
from ..sources import calendar_source
from .text import HOLES, LEVEL, TICKS, TWO_TYPES, frame, registry, series

QUERIES, ORACLES, query = registry()
T = B.read_table


def plain(name: str, sql: str, table: str, fn) -> None:
    """A query on one table: ``fn`` of its DataFrame."""
    query(name, sql)(lambda s, d: fn(T(s, d, table)))


# ---- scans, sources, sinks -------------------------------------------------------------------------------------------------

query("scan_parquet", "SELECT l_orderkey, l_extendedprice FROM lineitem WHERE l_quantity > 45")(lambda s, d: T(s, d, "lineitem", ["l_orderkey", "l_extendedprice"], "l_quantity > 45"))


def roundtrip(fmt: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        path = scratch(s, fmt)
        B.write_series(B.level_holes(s, d), fmt, path)
        return result(B.read_series(s, fmt, path, B.ORDERS))

    return run


for _fmt in ("xml", "csv", "json", "orc"):
    query(f"{_fmt}_roundtrip", series(HOLES, "SELECT * FROM holes"))(roundtrip(_fmt))


@query("store_bucketed", series(TICKS, f"SELECT series_id, idx, max(v) OVER {frame(20)} AS v FROM ticks"))
def store_bucketed(s: SparkSession, d: str) -> DataFrame:
    """Stored by (series_id, seg) with its halo, then a window that needs no shuffle."""
    a = G.segment(B.ticks(s, d), 4096, 19, 0)
    path = scratch(s, "bucketed")
    name = f"calseries_{path.rsplit('-', 1)[1]}"
    a.df.write.mode("overwrite").option("path", path).bucketBy(8, "series_id", "seg").sortBy("series_id", "seg", "idx").saveAsTable(name)
    stored = a.with_df(s.table(name))
    return result(G.core(W.mmax(stored, 20)))


@query("append_sink", f"WITH {TICKS} SELECT count(*) AS n, CAST(max(idx // 1024) AS BIGINT) AS last_seg, round(sum(CASE WHEN idx // 1024 = 1 THEN 0 ELSE v END), 2) AS total FROM ticks")
def append_sink(s: SparkSession, d: str) -> DataFrame:
    path, a = scratch(s, "append"), B.ticks(s, d)
    B.append_segments(a, path, 1024)
    B.append_segments(a.with_df(a.df.where("idx BETWEEN 1024 AND 2047").withColumn("v", F.lit(0.0))), path, 1024)
    return s.read.parquet(path).agg(F.count(F.lit(1)).alias("n"), F.max("seg").cast("long").alias("last_seg"), snap(F.sum("v"), 2).alias("total"))


query("json_props", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")(
    lambda s, d: T(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k")))
query("gen_ramp", f"WITH {LEVEL} SELECT 'ramp' AS series_id, CAST(idx AS BIGINT) AS idx, CAST(idx AS DOUBLE) AS v FROM level")(lambda s, d: B.generated(B.level(s, d)).df)


@query("source_calendar", "SELECT CAST(i AS BIGINT) AS idx, TIMESTAMP '2024-01-01' + to_minutes(CAST(15 * i AS BIGINT)) AS t FROM range(100) r(i)")
def source_calendar(s: SparkSession, d: str) -> DataFrame:
    calendar_source.register(s)
    return s.read.format("calendar").option("start", "2024-01-01").option("seconds", 900).option("n", 100).load()


@query("sql_view_series", f"WITH {LEVEL} SELECT count(*) AS n, round(max(v), 2) AS top FROM level WHERE idx < 1000")
def sql_view_series(s: SparkSession, d: str) -> DataFrame:
    B.register(B.level(s, d), "level_series")
    return s.sql("SELECT count(*) AS n, max(v) AS top FROM level_series WHERE t < TIMESTAMP_NTZ '1997-09-27 00:00:00'").select("n", snap(F.col("top"), 2).alias("top"))


# ---- filters and projections ----------------------------------------------------------------------------------------------

ORD = ["o_orderkey", "o_totalprice"]
plain("filter_cmp", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice > 400000 AND o_orderstatus <> 'F'", "orders", lambda t: t.where("o_totalprice > 400000 AND o_orderstatus <> 'F'").select(*ORD))
plain("filter_between", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice BETWEEN 100000 AND 120000", "orders", lambda t: t.where(F.col("o_totalprice").between(100000, 120000)).select(*ORD))
plain("filter_in", "SELECT p_partkey, p_size FROM part WHERE p_size IN (1, 7, 23)", "part", lambda t: t.where(F.col("p_size").isin(1, 7, 23)).select("p_partkey", "p_size"))
plain("filter_like", "SELECT p_partkey, p_brand FROM part WHERE p_brand LIKE '%1%' AND regexp_matches(p_type, '[AEIOU]')", "part", lambda t: t.where(F.col("p_brand").like("%1%") & F.col("p_type").rlike("[AEIOU]")).select("p_partkey", "p_brand"))
plain("filter_null", "SELECT count(*) AS n FROM events WHERE nullif(event_type, 'click') IS NULL", "events", lambda t: t.where(F.nullif("event_type", F.lit("click")).isNull()).agg(F.count(F.lit(1)).alias("n")))
plain("filter_logic", "SELECT count(*) AS n FROM lineitem WHERE (l_quantity < 10 OR l_discount > 0.05) AND NOT l_returnflag = 'N'", "lineitem", lambda t: t.where(((F.col("l_quantity") < 10) | (F.col("l_discount") > 0.05)) & ~(F.col("l_returnflag") == "N")).agg(F.count(F.lit(1)).alias("n")))
plain("project_expr", "SELECT l_orderkey, l_linenumber, l_partkey, round(l_extendedprice * (1 - l_discount), 3) AS net FROM lineitem", "lineitem", lambda t: t.select("l_orderkey", "l_linenumber", "l_partkey", snap(F.col("l_extendedprice") * (1 - F.col("l_discount")), 3).alias("net")))
plain("project_cast", "SELECT o_orderkey, CAST(o_orderkey AS VARCHAR) AS k, CAST(o_orderdate AS DATE) AS day FROM orders", "orders", lambda t: t.select("o_orderkey", F.col("o_orderkey").cast("string").alias("k"), F.col("o_orderdate").cast("date").alias("day")))
plain("project_case", "SELECT o_orderkey, CASE WHEN o_totalprice > 300000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS band FROM orders", "orders",
      lambda t: t.select("o_orderkey", F.when(F.col("o_totalprice") > 300000, "high").when(F.col("o_totalprice") > 100000, "mid").otherwise("low").alias("band")))
plain("distinct_rows", "SELECT DISTINCT role, turn FROM conversations", "conversations", lambda t: t.select("role", "turn").distinct())
plain("dedup_latest", "SELECT user_id, event_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) AS k FROM events) WHERE k = 1", "events",
      lambda t: t.withColumn("k", F.row_number().over(Window.partitionBy("user_id").orderBy(F.desc("ts"), F.desc("event_id")))).where("k = 1").select("user_id", "event_id"))
plain("sample_mod", "SELECT event_id FROM events WHERE event_id % 7 = 3", "events", lambda t: t.where(F.pmod("event_id", F.lit(7)) == 3).select("event_id"))
plain("explode_vector", "SELECT vec_id, CAST(i - 1 AS INTEGER) AS pos, CAST(embedding[i] AS DOUBLE) AS x FROM embeddings, range(1, 65) r(i)", "embeddings", lambda t: t.select("vec_id", F.posexplode("embedding").alias("pos", "x")).select("vec_id", "pos", F.col("x").cast("double").alias("x")))

# ---- joins -----------------------------------------------------------------------------------------------------------------


@query("join_broadcast", "SELECT p_brand, count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY ALL")
def join_broadcast(s: SparkSession, d: str) -> DataFrame:
    l, p = T(s, d, "lineitem", ["l_partkey", "l_quantity"]), T(s, d, "part", ["p_partkey", "p_brand"])
    return l.join(p, l.l_partkey == p.p_partkey).groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"), snap(F.sum("l_quantity"), 2).alias("q"))


def orders_lines(hint: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        o, l = T(s, d, "orders", ["o_orderkey", "o_orderpriority"]), T(s, d, "lineitem", ["l_orderkey", "l_quantity"])
        return o.join(l.hint(hint), o.o_orderkey == l.l_orderkey).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), snap(F.sum("l_quantity"), 2).alias("q"))

    return run


for _name, _hint in (("join_sortmerge", "merge"), ("join_shuffle_hash", "shuffle_hash")):
    query(_name, "SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL")(orders_lines(_hint))

CO = "customer LEFT JOIN (SELECT o_custkey, count(*) AS n FROM orders GROUP BY ALL) ON c_custkey = o_custkey"


def customers(how: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        c, o = T(s, d, "customer", ["c_custkey"]), T(s, d, "orders", ["o_custkey"]).groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
        return (c.join(o, c.c_custkey == o.o_custkey, how) if how != "right" else o.join(c, c.c_custkey == o.o_custkey, how)).select("c_custkey", "n")

    return run


query("join_left", f"SELECT c_custkey, n FROM {CO}")(customers("left"))
query("join_right", f"SELECT c_custkey, n FROM {CO}")(customers("right"))
query("join_full", f"WITH {TWO_TYPES} SELECT CAST(coalesce(e1.idx, e2.idx) AS BIGINT) AS idx, round(e1.v, 4) AS a, round(e2.v, 4) AS b FROM e1 FULL JOIN e2 ON e1.idx = e2.idx")(
    lambda s, d: B.of_type(s, d, "click").df.select("idx", snap(F.col("v"), 4).alias("a")).join(B.of_type(s, d, "view").df.select("idx", snap(F.col("v"), 4).alias("b")), "idx", "full"))
query("join_semi", "SELECT c_custkey FROM customer SEMI JOIN orders ON c_custkey = o_custkey")(lambda s, d: T(s, d, "customer").join(T(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"))
query("join_anti", "SELECT doc_id FROM documents ANTI JOIN labels USING (doc_id)")(lambda s, d: T(s, d, "documents", ["doc_id"]).join(T(s, d, "labels", ["doc_id"]), "doc_id", "left_anti"))
query("join_cross", "SELECT r_name, n_name FROM region CROSS JOIN nation")(lambda s, d: T(s, d, "region", ["r_name"]).crossJoin(T(s, d, "nation", ["n_name"])))
query("join_theta", "SELECT a.n_nationkey AS x, b.n_nationkey AS y FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey AND a.n_nationkey <> b.n_nationkey")(
    lambda s, d: T(s, d, "nation").alias("a").join(T(s, d, "nation").alias("b"), F.expr("a.n_regionkey < b.n_regionkey AND a.n_nationkey <> b.n_nationkey")).select(F.col("a.n_nationkey").alias("x"), F.col("b.n_nationkey").alias("y")))
IV = "(SELECT i AS iv, i * 50 AS a, i * 50 + 30 AS b FROM range(20) r(i))"


@query("join_range", f"SELECT CAST(iv AS BIGINT) AS iv, count(*) AS n FROM part JOIN {IV} ON p_partkey >= a AND p_partkey < b GROUP BY ALL")
def join_range(s: SparkSession, d: str) -> DataFrame:
    iv = s.range(20).select(F.col("id").alias("iv"), (F.col("id") * 50).alias("a"), (F.col("id") * 50 + 30).alias("b"))
    return J.range_join(T(s, d, "part", ["p_partkey"]), iv, "p_partkey", "a", "b", 64).groupBy("iv").agg(F.count(F.lit(1)).alias("n"))


@query("join_interval", "SELECT CAST(x.i AS BIGINT) AS seg, CAST(y.i AS BIGINT) AS q FROM range(30) x(i) JOIN range(12) y(i) ON x.i * 100 <= y.i * 230 + 150 AND y.i * 230 <= x.i * 100 + 99")
def join_interval(s: SparkSession, d: str) -> DataFrame:
    segs = s.range(30).select(F.col("id").alias("seg"), (F.col("id") * 100).alias("l_start"), (F.col("id") * 100 + 99).alias("l_end"))
    want = s.range(12).select(F.col("id").alias("q"), (F.col("id") * 230).alias("r_start"), (F.col("id") * 230 + 150).alias("r_end"))
    return J.overlap_join(segs, want, 128).select("seg", "q")


def asof_run(tolerance: float | None, direction: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        e = T(s, d, "events", ["user_id", "ts", "event_id", "event_type", "value"])
        left, right = e.where("event_type = 'purchase'").drop("event_type", "value"), e.where("event_type = 'view'").select("user_id", "ts", "event_id", "value")
        out = J.asof(left, right, ["user_id"], "ts", ["value"], tolerance, direction, tie=["event_id"])
        return out.select("event_id", F.col("r_value").alias("seen"))

    return run


def asof_sql(cond: str, order: str, extra: str = "") -> str:
    return f"""SELECT event_id, seen FROM (SELECT p.event_id, v.value AS seen, row_number() OVER (PARTITION BY p.event_id ORDER BY {order}) AS k
      FROM (SELECT * FROM events WHERE event_type = 'purchase') p LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND {cond}{extra}) WHERE k = 1"""


query("join_asof", asof_sql("v.ts <= p.ts", "v.ts DESC, v.event_id DESC"))(asof_run(None, "backward"))
query("join_asof_tolerance", asof_sql("v.ts <= p.ts AND v.ts >= p.ts - INTERVAL 12 HOUR", "v.ts DESC, v.event_id DESC"))(asof_run(43200.0, "backward"))
query("join_asof_forward", asof_sql("v.ts >= p.ts", "v.ts, v.event_id"))(asof_run(None, "forward"))
query("join_star", "SELECT r_name, p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")(
    lambda s, d: T(s, d, "lineitem", ["l_partkey", "l_suppkey"]).join(T(s, d, "part", ["p_partkey", "p_brand"]), F.col("l_partkey") == F.col("p_partkey")).join(T(s, d, "supplier", ["s_suppkey", "s_nationkey"]), F.col("l_suppkey") == F.col("s_suppkey"))
    .join(T(s, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(T(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name", "p_brand").agg(F.count(F.lit(1)).alias("n")))
query("join_self_shift", f"WITH {LEVEL} SELECT CAST(a.idx AS BIGINT) AS idx, round(a.v - b.v, 4) AS v FROM level a JOIN level b ON a.idx = b.idx + 3")(
    lambda s, d: (lambda x: x.join(x.select((F.col("idx") + 3).alias("idx"), F.col("v").alias("w")), "idx").select("idx", snap(F.col("v") - F.col("w"), 4).alias("v")))(B.level(s, d).df))
query("join_nullsafe", "WITH a AS (SELECT nullif(p_size % 5, 0) AS k, count(*) AS n FROM part GROUP BY ALL), b AS (SELECT nullif(p_size % 3, 0) AS j, count(*) AS m FROM part GROUP BY ALL) SELECT k, n, m FROM a JOIN b ON a.k IS NOT DISTINCT FROM b.j")(
    lambda s, d: (lambda p: p.groupBy(F.nullif(F.col("p_size") % 5, F.lit(0)).alias("k")).agg(F.count(F.lit(1)).alias("n")).join(p.groupBy(F.nullif(F.col("p_size") % 3, F.lit(0)).alias("j")).agg(F.count(F.lit(1)).alias("m")), F.col("k").eqNullSafe(F.col("j"))).select("k", "n", "m"))(T(s, d, "part")))
query("join_salted", "SELECT e.event_type, count(*) AS n FROM events e JOIN (SELECT DISTINCT event_type FROM events) k USING (event_type) GROUP BY ALL")(
    lambda s, d: (lambda e: J.salted_join(e, e.select("event_type").distinct(), "event_type", 8).groupBy("event_type").agg(F.count(F.lit(1)).alias("n")))(T(s, d, "events", ["event_id", "event_type"])))

# ---- aggregates ------------------------------------------------------------------------------------------------------------

plain("agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS q, round(avg(l_extendedprice), 3) AS p, min(l_discount) AS lo, max(l_tax) AS hi FROM lineitem GROUP BY ALL", "lineitem",
      lambda t: t.groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), snap(F.sum("l_quantity"), 2).alias("q"), snap(F.avg("l_extendedprice"), 3).alias("p"), F.min("l_discount").alias("lo"), F.max("l_tax").alias("hi")))
plain("agg_decimal", "SELECT o_orderstatus, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS VARCHAR) AS total FROM orders GROUP BY ALL", "orders", lambda t: t.groupBy("o_orderstatus").agg(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("string").alias("total")))
plain("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY ALL", "events", lambda t: t.groupBy("event_type").agg(F.count_distinct("user_id").alias("users")))
query("agg_approx_distinct")(lambda s, d: T(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users")))
plain("agg_filter", "SELECT event_type, count(*) FILTER (value > 50) AS high, count(*) AS n FROM events GROUP BY ALL", "events", lambda t: t.groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("high"), F.count(F.lit(1)).alias("n")))
plain("agg_having", "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY ALL HAVING count(*) > 610", "lineitem", lambda t: t.groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n")).where("n > 610"))
plain("agg_global", "SELECT count(*) AS n, round(sum(value), 2) AS total FROM events", "events", lambda t: t.agg(F.count(F.lit(1)).alias("n"), snap(F.sum("value"), 2).alias("total")))
plain("agg_stddev_corr", "SELECT l_returnflag, round(stddev_samp(l_quantity), 5) AS sd, round(var_pop(l_discount), 8) AS vp, round(corr(l_quantity, l_extendedprice), 5) AS r FROM lineitem GROUP BY ALL", "lineitem",
      lambda t: t.groupBy("l_returnflag").agg(snap(F.stddev_samp("l_quantity"), 5).alias("sd"), snap(F.var_pop("l_discount"), 8).alias("vp"), snap(F.corr("l_quantity", "l_extendedprice"), 5).alias("r")))
plain("agg_regr", "SELECT l_returnflag, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(regr_intercept(l_extendedprice, l_quantity), 3) AS icpt FROM lineitem GROUP BY ALL", "lineitem",
      lambda t: t.groupBy("l_returnflag").agg(snap(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"), snap(F.regr_intercept("l_extendedprice", "l_quantity"), 3).alias("icpt")))
plain("agg_percentile", "SELECT event_type, round(quantile_cont(value, 0.25), 4) AS p25, round(median(value), 4) AS p50 FROM events GROUP BY ALL", "events", lambda t: t.groupBy("event_type").agg(snap(F.percentile("value", F.lit(0.25)), 4).alias("p25"), snap(F.median("value"), 4).alias("p50")))
plain("agg_minmax_by", "SELECT user_id, arg_min(event_id, (ts, event_id)) AS first_event, arg_max(event_id, (ts, event_id)) AS last_event FROM events GROUP BY ALL", "events",
      lambda t: t.groupBy("user_id").agg(F.min_by("event_id", F.struct("ts", "event_id")).alias("first_event"), F.max_by("event_id", F.struct("ts", "event_id")).alias("last_event")))
plain("agg_collect_sorted", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY ALL", "nation", lambda t: t.groupBy("n_regionkey").agg(F.concat_ws(",", F.sort_array(F.collect_list("n_name"))).alias("names")))
plain("agg_bool", "SELECT o_orderpriority, bool_and(o_totalprice > 1000) AS every_, bool_or(o_totalprice > 490000) AS some_ FROM orders GROUP BY ALL", "orders", lambda t: t.groupBy("o_orderpriority").agg(F.bool_and(F.col("o_totalprice") > 1000).alias("every_"), F.bool_or(F.col("o_totalprice") > 490000).alias("some_")))


def viewed(table: str, sql: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        T(s, d, table).createOrReplaceTempView(f"cs_{table}")
        return s.sql(sql.replace(f" {table}", f" cs_{table}"))

    return run


SETS = "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(grouping(l_returnflag) AS INTEGER) AS g FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())"
query("grouping_sets", SETS)(viewed("lineitem", SETS))
plain("cube_style", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)", "orders", lambda t: t.cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n")))
plain("rollup_calendar", "SELECT CAST(y AS INTEGER) AS y, CAST(m AS INTEGER) AS m, count(*) AS n FROM (SELECT year(o_orderdate) AS y, month(o_orderdate) AS m FROM orders) GROUP BY ROLLUP (y, m)", "orders",
      lambda t: t.select(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).rollup("y", "m").agg(F.count(F.lit(1)).alias("n")))
plain("pivot_types", "SELECT user_id % 10 AS g, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view_ FROM events GROUP BY ALL", "events",
      lambda t: t.groupBy((F.col("user_id") % 10).alias("g")).pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).select("g", F.coalesce("click", F.lit(0)).alias("click"), F.coalesce("view", F.lit(0)).alias("view_")))
query("unpivot_quote", "SELECT l_orderkey, k, v FROM (SELECT l_orderkey, sum(l_quantity) AS q, max(l_linenumber) + 0.0::DOUBLE AS m FROM lineitem GROUP BY ALL) UNPIVOT (v FOR k IN (q, m))")(
    lambda s, d: T(s, d, "lineitem").groupBy("l_orderkey").agg(F.sum("l_quantity").alias("q"), F.max("l_linenumber").cast("double").alias("m")).unpivot("l_orderkey", ["q", "m"], "k", "v"))

# ---- window functions --------------------------------------------------------------------------------------------------------

RANK = "(PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"


def cust() -> WindowSpec:
    return Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


def prio() -> WindowSpec:
    return Window.partitionBy("p_brand").orderBy("p_size")




plain("win_row_number", f"SELECT o_orderkey, CAST(row_number() OVER {RANK} AS INTEGER) AS r FROM orders", "orders", lambda t: t.select("o_orderkey", F.row_number().over(cust()).alias("r")))
query("win_rank", "SELECT p_partkey, CAST(rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS INTEGER) AS r FROM part")(lambda s, d: T(s, d, "part").select("p_partkey", F.rank().over(prio()).alias("r")))
query("win_dense_rank", "SELECT p_partkey, CAST(dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS INTEGER) AS r FROM part")(lambda s, d: T(s, d, "part").select("p_partkey", F.dense_rank().over(prio()).alias("r")))
query("win_percent_rank", "SELECT p_partkey, round(percent_rank() OVER (PARTITION BY p_brand ORDER BY p_size), 6) AS r FROM part")(lambda s, d: T(s, d, "part").select("p_partkey", snap(F.percent_rank().over(prio()), 6).alias("r")))
query("win_cume_dist", "SELECT p_partkey, round(cume_dist() OVER (PARTITION BY p_brand ORDER BY p_size), 6) AS r FROM part")(lambda s, d: T(s, d, "part").select("p_partkey", snap(F.cume_dist().over(prio()), 6).alias("r")))
plain("win_ntile", f"SELECT o_orderkey, CAST(ntile(4) OVER {RANK} AS INTEGER) AS r FROM orders", "orders", lambda t: t.select("o_orderkey", F.ntile(4).over(cust()).alias("r")))
plain("win_lag_lead", f"SELECT o_orderkey, lag(o_orderkey) OVER {RANK} AS prev, lead(o_orderkey, 2) OVER {RANK} AS nxt FROM orders", "orders", lambda t: t.select("o_orderkey", F.lag("o_orderkey").over(cust()).alias("prev"), F.lead("o_orderkey", 2).over(cust()).alias("nxt")))
ROWS = "ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"
plain("win_first_last_nth", f"SELECT o_orderkey, first_value(o_orderkey) OVER w AS f, last_value(o_orderkey) OVER w AS l, nth_value(o_orderkey, 2) OVER w AS n FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey {ROWS}", "orders",
      lambda t: (lambda w: t.select("o_orderkey", F.first("o_orderkey").over(w).alias("f"), F.last("o_orderkey").over(w).alias("l"), F.nth_value("o_orderkey", 2).over(w).alias("n")))(cust().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
plain("win_ignore_nulls", f"SELECT o_orderkey, last_value(CASE WHEN o_orderstatus = 'F' THEN o_orderkey END IGNORE NULLS) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING) AS f FROM orders", "orders",
      lambda t: t.select("o_orderkey", F.last(F.when(F.col("o_orderstatus") == "F", F.col("o_orderkey")), ignorenulls=True).over(cust().rowsBetween(Window.unboundedPreceding, 0)).alias("f")))


def framed(name: str, clause: str, w) -> None:
    plain(name, f"SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey {clause}), 2) AS s FROM orders", "orders", lambda t: t.select("o_orderkey", snap(F.sum("o_totalprice").over(w()), 2).alias("s")))


framed("win_rows_frame", "ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW", lambda: cust().rowsBetween(-2, 0))
framed("win_centred", "ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING", lambda: cust().rowsBetween(-1, 1))
framed("win_unbounded", "ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING", lambda: cust().rowsBetween(Window.unboundedPreceding, 0))
framed("win_range_frame", "ORDER BY o_orderkey RANGE BETWEEN 500 PRECEDING AND CURRENT ROW", lambda: Window.partitionBy("o_custkey").orderBy("o_orderkey").rangeBetween(-500, 0))
INTERVAL = "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate RANGE BETWEEN INTERVAL 90 DAY PRECEDING AND CURRENT ROW) AS n FROM orders"
query("win_range_interval", INTERVAL)(viewed("orders", INTERVAL.replace("INTERVAL 90 DAY", "INTERVAL '90' DAY")))
query("win_percentile", series(LEVEL, f"SELECT series_id, idx, quantile_cont(v, 0.75) OVER {frame(12)} AS v FROM level"))(lambda s, d: result(W.mmedian(B.level(s, d), 12, 0.75)))
plain("win_corr", "SELECT l_orderkey, n, r FROM (SELECT l_orderkey, count(*) OVER w AS n, round(sum(l_quantity * l_discount) OVER w, 4) AS r FROM lineitem WINDOW w AS (PARTITION BY l_orderkey))", "lineitem",
      lambda t: (lambda w: t.select("l_orderkey", F.count(F.lit(1)).over(w).alias("n"), snap(F.sum(F.col("l_quantity") * F.col("l_discount")).over(w), 4).alias("r")))(Window.partitionBy("l_orderkey")))

# ---- sort, limit, sets, sub-queries ---------------------------------------------------------------------------------------------

plain("sort_multi", "SELECT c_custkey, c_nationkey FROM customer ORDER BY c_nationkey DESC, c_custkey", "customer", lambda t: t.orderBy(F.desc("c_nationkey"), "c_custkey").select("c_custkey", "c_nationkey"))
plain("sort_nulls", "SELECT k, n FROM (SELECT nullif(p_size, 5) AS k, count(*) AS n FROM part GROUP BY ALL) ORDER BY k NULLS LAST", "part", lambda t: t.groupBy(F.nullif("p_size", F.lit(5)).alias("k")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.asc_nulls_last("k")))
plain("limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 20 OFFSET 30", "orders", lambda t: t.orderBy("o_orderkey").offset(30).limit(20).select("o_orderkey"))
plain("topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10", "orders", lambda t: t.orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select(*ORD))
plain("topk_per_group", "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) WHERE k <= 2", "orders",
      lambda t: t.withColumn("k", F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("k <= 2").select("o_custkey", "o_orderkey"))


def sets(name: str, sql: str, fn) -> None:
    a, b = "SELECT c_nationkey AS k FROM customer WHERE c_nationkey < 15", "SELECT s_nationkey AS k FROM supplier WHERE s_nationkey > 5"
    query(name, f"{a} {sql} {b}")(lambda s, d: fn(T(s, d, "customer").where("c_nationkey < 15").select(F.col("c_nationkey").alias("k")), T(s, d, "supplier").where("s_nationkey > 5").select(F.col("s_nationkey").alias("k"))))


sets("set_union_all", "UNION ALL", lambda a, b: a.unionAll(b))
sets("set_union", "UNION", lambda a, b: a.union(b).distinct())
sets("set_intersect", "INTERSECT", lambda a, b: a.intersect(b))
sets("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b))
sets("set_except", "EXCEPT", lambda a, b: a.subtract(b))
sets("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))
query("set_union_by_name", "SELECT r_regionkey AS k, r_name AS name FROM region UNION ALL BY NAME SELECT n_name AS name, n_nationkey AS k FROM nation")(
    lambda s, d: T(s, d, "region").select(F.col("r_regionkey").alias("k"), F.col("r_name").alias("name")).unionByName(T(s, d, "nation").select(F.col("n_name").alias("name"), F.col("n_nationkey").alias("k"))))


def sql_query(name: str, sql: str, tables: list[str]) -> None:
    """The same text in both engines."""

    def there(s: SparkSession, d: str) -> DataFrame:
        text = sql
        for t in tables:
            T(s, d, t).createOrReplaceTempView(f"cs_{t}")
            text = text.replace(f"{{{t}}}", f"cs_{t}")
        return s.sql(text)

    query(name, sql.format(**{t: t for t in tables}))(there)


sql_query("subq_scalar", "SELECT o_orderkey FROM {orders} WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.8 FROM {orders})", ["orders"])
sql_query("subq_exists", "SELECT c_custkey FROM {customer} c WHERE EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 400000)", ["customer", "orders"])
sql_query("subq_in", "SELECT c_custkey FROM {customer} WHERE c_nationkey IN (SELECT n_nationkey FROM {nation} WHERE n_regionkey = 1)", ["customer", "nation"])
sql_query("subq_correlated", "SELECT o_orderkey FROM {orders} o WHERE o_totalprice >= (SELECT max(o_totalprice) FROM {orders} i WHERE i.o_custkey = o.o_custkey)", ["orders"])
sql_query("lateral_join", "SELECT n_name, r.r_name FROM {nation} n, LATERAL (SELECT r_name FROM {region} r WHERE r.r_regionkey = n.n_regionkey) r", ["nation", "region"])
sql_query("cte_chain", "WITH a AS (SELECT o_custkey, count(*) AS n FROM {orders} GROUP BY o_custkey), b AS (SELECT n, count(*) AS k FROM a GROUP BY n) SELECT n, k FROM b WHERE k > 1", ["orders"])

# ---- functions ---------------------------------------------------------------------------------------------------------------------

sql_query("fn_string", "SELECT p_partkey, upper(p_name) AS u, lower(p_brand) AS l, substring(p_name, 1, 3) AS s3, CAST(length(p_type) AS BIGINT) AS n, concat_ws('-', p_brand, p_type) AS cw, lpad(p_brand, 12, '*') AS pad, trim(concat(' ', p_brand, ' ')) AS tr, reverse(p_brand) AS rv, repeat(p_brand, 2) AS rp, translate(p_brand, 'abc', 'xyz') AS tl FROM {part}", ["part"])
plain("fn_regexp", "SELECT p_partkey, regexp_extract(p_brand, '([0-9]+)', 1) AS digits, regexp_replace(p_type, '[AEIOU]', '_', 'g') AS masked FROM part", "part", lambda t: t.select("p_partkey", F.regexp_extract("p_brand", "([0-9]+)", 1).alias("digits"), F.regexp_replace("p_type", "[AEIOU]", "_").alias("masked")))
plain("fn_date", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS m, CAST(o_orderdate AS DATE) + 30 AS plus30, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(quarter(o_orderdate) AS INTEGER) AS q, last_day(CAST(o_orderdate AS DATE)) AS ld, strftime(o_orderdate, '%Y/%m/%d') AS txt FROM orders", "orders",
      lambda t: t.select("o_orderkey", F.trunc("o_orderdate", "month").alias("m"), F.date_add(F.col("o_orderdate").cast("date"), 30).alias("plus30"), F.datediff("o_orderdate", F.lit("1995-01-01")).alias("days"), F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"), F.last_day("o_orderdate").alias("ld"), F.date_format("o_orderdate", "yyyy/MM/dd").alias("txt")))
plain("fn_interval", "SELECT event_id, ts + INTERVAL 90 MINUTE AS later FROM events", "events", lambda t: t.select("event_id", (F.col("ts") + F.expr("INTERVAL '90' MINUTE")).alias("later")))
plain("fn_math", "SELECT l_orderkey, l_linenumber, l_partkey, abs(l_quantity - 25) AS a, CAST(floor(l_extendedprice) AS BIGINT) AS fl, CAST(ceil(l_extendedprice) AS BIGINT) AS ce, round(sqrt(l_quantity), 6) AS sq, round(ln(l_extendedprice), 6) AS ln_, CAST(sign(l_discount - 0.05) AS DOUBLE) AS sg, greatest(l_discount, l_tax) AS g, least(l_discount, l_tax) AS l FROM lineitem", "lineitem",
      lambda t: t.select("l_orderkey", "l_linenumber", "l_partkey", F.abs(F.col("l_quantity") - 25).alias("a"), F.floor("l_extendedprice").alias("fl"), F.ceil("l_extendedprice").alias("ce"), snap(F.sqrt("l_quantity"), 6).alias("sq"), snap(F.ln("l_extendedprice"), 6).alias("ln_"), F.signum(F.col("l_discount") - 0.05).alias("sg"), F.greatest("l_discount", "l_tax").alias("g"), F.least("l_discount", "l_tax").alias("l")))
plain("fn_trig", "SELECT event_id, round(sin(value), 6) AS s, round(cos(value), 6) AS c, round(atan2(value, 10), 6) AS a FROM events", "events", lambda t: t.select("event_id", snap(F.sin("value"), 6).alias("s"), snap(F.cos("value"), 6).alias("c"), snap(F.atan2(F.col("value"), F.lit(10.0)), 6).alias("a")))
plain("fn_array", "SELECT vec_id, len(embedding) AS n, CAST(embedding[3] AS DOUBLE) AS third, CAST(list_max(embedding) AS DOUBLE) AS top FROM embeddings", "embeddings", lambda t: t.select("vec_id", F.size("embedding").cast("long").alias("n"), F.element_at("embedding", 3).cast("double").alias("third"), F.array_max("embedding").cast("double").alias("top")))
plain("fn_array_hof", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 5) AS sq, len(list_filter(embedding, lambda x: x > 0)) AS pos FROM embeddings", "embeddings",
      lambda t: t.select("vec_id", snap(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x), F.lit(0.0), lambda a, x: a + x), 5).alias("sq"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("pos")))
plain("fn_map", "SELECT r_regionkey, r_name AS name, length(r_name) AS n FROM region", "region", lambda t: (lambda m: t.select("r_regionkey", F.element_at(m, "name").alias("name"), F.length(F.element_at(m, "name")).cast("long").alias("n")))(F.map_from_arrays(F.array(F.lit("name"), F.lit("key")), F.array("r_name", F.col("r_regionkey").cast("string")))))
plain("fn_struct", "SELECT n_nationkey, n_name AS a, n_regionkey AS b FROM nation", "nation", lambda t: t.select("n_nationkey", F.struct(F.col("n_name").alias("a"), F.col("n_regionkey").alias("b")).alias("s")).select("n_nationkey", "s.a", "s.b"))
plain("fn_json", "SELECT event_id, json_extract_string(props, '$.k') AS k FROM events", "events", lambda t: t.select("event_id", F.get_json_object("props", "$.k").alias("k")))
sql_query("fn_conditional", "SELECT p_partkey, coalesce(nullif(p_size, 1), -1) AS a, CASE WHEN p_size > 25 THEN 'big' ELSE 'small' END AS b FROM {part}", ["part"])
query("fn_nan", f"WITH {HOLES} SELECT count(*) FILTER (isnan(v)) AS unknowns, round(sum(CASE WHEN isnan(v) THEN 0 ELSE v END), 2) AS total FROM holes")(lambda s, d: B.level_holes(s, d).df.agg(F.count_if(F.isnan("v")).alias("unknowns"), snap(F.sum(F.nanvl("v", F.lit(0.0))), 2).alias("total")))
plain("fn_hash", "SELECT n_nationkey, md5(n_name) AS m, sha256(n_name) AS s, upper(hex(n_name)) AS h FROM nation", "nation", lambda t: t.select("n_nationkey", F.md5("n_name").alias("m"), F.sha2("n_name", 256).alias("s"), F.hex("n_name").alias("h")))
