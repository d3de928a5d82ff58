"""Queries on segments, names, the cache, rewriting, the ring and the cost model."""

from __future__ import annotations


from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans import cost as C
from ..plans import expr as X
from ..plans import planner as P
from ..plans import segments as G
from ..plans.cache import Cache
from ..plans.rewrite import canonical
from ..series import result, snap
from ..sources import base as B
from .text import LEVEL, TICKS, TWO_TYPES, back, frame, registry, series

QUERIES, ORACLES, query = registry()


@query("segment_rows", f"WITH {LEVEL}, s AS (SELECT idx, v, unnest(range(greatest(0, (idx - 16) // 128 - CASE WHEN idx < 16 THEN 1 ELSE 0 END), (idx + 32) // 128 + 1)) AS seg FROM level) SELECT CAST(seg AS BIGINT) AS seg, count(*) AS n_rows, count(*) FILTER (idx // 128 = seg) AS n_core, round(sum(v), 2) AS total FROM s GROUP BY ALL")
def segment_rows(s: SparkSession, d: str) -> DataFrame:
    rows = G.segment(B.level(s, d), 128, 32, 16).df
    return rows.groupBy("seg").agg(F.count(F.lit(1)).alias("n_rows"), F.count_if("is_core").alias("n_core"), snap(F.sum("v"), 2).alias("total"))


@query("segment_counts", f"WITH {TICKS} SELECT series_id, CAST(idx // 1024 AS BIGINT) AS seg, count(*) AS n_core FROM ticks GROUP BY ALL")
def segment_counts(s: SparkSession, d: str) -> DataFrame:
    return G.segment_counts(B.ticks(s, d)).select("series_id", "seg", "n_core")


@query("segment_padding", f"WITH {TICKS} SELECT CAST(count(*) AS BIGINT) AS n, CAST((max(idx) // 1024 + 1) * 1024 - max(idx) - 1 AS BIGINT) AS padded FROM ticks")
def segment_padding(s: SparkSession, d: str) -> DataFrame:
    return G.pad_last(B.ticks(s, d), 1024).agg(F.count_if(~F.col("padding")).alias("n"), F.count_if("padding").alias("padded"))


NAMES = ["MAVG(level,10)", "SCALE(MOM(level,5),100)", "JOIN(MAVG(level,10),SCALE(RSI(level,14),100),SUM)"]


@query("name_hash", "SELECT n AS name, sha256(n) AS key FROM (VALUES ('MAVG(level;w=10)'), ('SCALE(MOM(level;k=5);s=100)'), ('JOIN(MAVG(level;w=10),SCALE(RSI(level;w=14);s=100);fn=SUM)')) t(n)")
def name_hash(s: SparkSession, d: str) -> DataFrame:
    return s.createDataFrame([(X.name(X.parse(t)),) for t in NAMES], "name string").select("name", F.sha2("name", 256).alias("key"))


SCALED = series(LEVEL, f"SELECT * FROM (SELECT series_id, idx, 100 * (v - {back(5)}) AS v FROM level) WHERE v IS NOT NULL", 2)


@query("rewrite_scale_mom", SCALED)
def rewrite_scale_mom(s: SparkSession, d: str) -> DataFrame:
    tree = canonical(X.parse("MOM(SCALE(level,100),5)"))
    if tree != canonical(X.parse("SCALE(MOM(level,5),100)")):
        raise AssertionError("equal trees with different names")
    return result(P.lower(tree, {"level": B.level(s, d)}, 256), 2)


BUY = "SEL(MAVG(MINUS(MAVG(level,12),MAVG(level,26)),9),gt,0)"
query("buy_fused", series(LEVEL, f"SELECT * FROM (SELECT series_id, idx, avg(m) OVER {frame(9)} AS v FROM (SELECT series_id, idx, avg(v) OVER {frame(12)} - avg(v) OVER {frame(26)} AS m FROM level)) WHERE v > 0", 3))(
    lambda s, d: result(P.lower(X.parse(BUY), {"level": B.level(s, d)}, 64), 3))
query("buy_interval", series(LEVEL, f"SELECT * FROM (SELECT series_id, idx, avg(m) OVER {frame(9)} AS v FROM (SELECT series_id, idx, avg(v) OVER {frame(12)} - avg(v) OVER {frame(26)} AS m FROM level)) WHERE v > 0 AND idx BETWEEN 800 AND 1200", 3))(
    lambda s, d: result(P.lower(X.parse(BUY), {"level": B.level(s, d)}, 128, (800, 1200)), 3))
AVG_MOM = series(LEVEL, f"SELECT * FROM (SELECT series_id, idx, avg(v) OVER {frame(10)} + 100 * (v - {back(5)}) AS v FROM level) WHERE v IS NOT NULL", 2)
query("join_avg_mom", AVG_MOM)(lambda s, d: result(P.lower(X.parse("JOIN(MAVG(level,10),SCALE(MOM(level,5),100),SUM)"), {"level": B.level(s, d)}, 512), 2))

AVG_RSI_TREE = "JOIN(MAVG(level,10),SCALE(RSI(level,14),100),SUM)"
AVG_RSI = series(f"{LEVEL}, d AS (SELECT series_id, idx, v, avg(v) OVER {frame(10)} AS m, v - {back(1)} AS d FROM level)", f"""SELECT series_id, idx, CASE WHEN n = 0 THEN NULL WHEN g + l = 0 THEN 'nan'::DOUBLE ELSE m + 100 * (100 * g / (g + l)) END AS v
  FROM (SELECT series_id, idx, m, sum(greatest(d, 0)) OVER {frame(14)} AS g, sum(greatest(-d, 0)) OVER {frame(14)} AS l, count(d) OVER {frame(14)} AS n FROM d) WHERE n > 0""", 3)


def cached(partial: bool):
    def run(s: SparkSession, d: str) -> DataFrame:
        from ..session import scratch

        bases, n, last = {"level": B.level(s, d)}, X.parse(AVG_RSI_TREE), 2404 // 512
        cache = Cache(s, scratch(s, "cache"), length=512)
        for child in n.children:
            segs = [(0, 1)] if partial else [(0, last)]
            P.execute(child, bases, segs, cache, 512, keep=True)
        return result(P.execute(n, bases, [(0, last)], cache, 512), 3)

    return run


query("exec_segmented_avg_rsi", AVG_RSI)(lambda s, d: result(P.lower(X.parse(AVG_RSI_TREE), {"level": B.level(s, d)}, 256), 3))
query("lower_chosen_length", AVG_RSI)(lambda s, d: result(P.lower(X.parse(AVG_RSI_TREE), {"level": B.level(s, d)}, None), 3))
query("exec_two_bases", series(TWO_TYPES, f"SELECT series_id, idx, avg(v) OVER {frame(12)} AS v FROM (SELECT series_id, idx, a.m - b.m AS v FROM (SELECT series_id, idx, avg(v) OVER {frame(6)} AS m FROM e1) a JOIN (SELECT series_id, idx, avg(v) OVER {frame(6)} AS m FROM e2) b USING (series_id, idx))", 5))(
    lambda s, d: result(P.lower(X.parse("MAVG(MINUS(MAVG(a,6),MAVG(b,6)),12)"), {"a": B.of_type(s, d, "click"), "b": B.of_type(s, d, "view")}, 128), 5))


@query("cached_canonical", SCALED)
def cached_canonical(s: SparkSession, d: str) -> DataFrame:
    """Two names of one series: what the first stores the second reads."""
    from ..session import scratch

    bases, last = {"level": B.level(s, d)}, 2404 // 512
    cache = Cache(s, scratch(s, "cache"), length=512)
    P.execute(X.parse("SCALE(MOM(level,5),100)"), bases, [(0, last)], cache, 512, keep=True)
    out = P.execute(X.parse("MOM(SCALE(level,100),5)"), bases, [(0, last)], cache, 512)
    if cache.counts["segment_hits"] != last + 1:
        raise AssertionError("an equal tree wasn't found")
    return result(out, 2)


@query("cached_all_nodes", AVG_RSI)
def cached_all_nodes(s: SparkSession, d: str) -> DataFrame:
    """Every sub-tree computed on the way is published; another order of the same sum is all read."""
    from ..session import scratch

    bases, last = {"level": B.level(s, d)}, 2404 // 512
    cache = Cache(s, scratch(s, "cache"), length=512)
    P.execute(X.parse(AVG_RSI_TREE), bases, [(0, 1)], cache, 512, keep="all")
    P.execute(X.parse(AVG_RSI_TREE), bases, [(0, last)], cache, 512, keep="all")
    if {e.name for e in cache.catalog.all()} != {"MAVG(level;w=10)", "RSI(level;w=14)", "SCALE(RSI(level;w=14);s=100)", X.name(X.parse(AVG_RSI_TREE))}:
        raise AssertionError("a sub-tree is missing from the directory")
    return result(P.execute(X.parse("PLUS(SCALE(RSI(level,14),100),MAVG(level,10))"), bases, [(0, last)], cache, 512), 3)


query("cached_join_avg_rsi", AVG_RSI)(cached(False))
query("cached_partial", AVG_RSI)(cached(True))


@query("multi_query_shared", series(LEVEL, f"SELECT * FROM (SELECT series_id, idx, 2 * avg(v) OVER {frame(10)} + (v - {back(5)}) AS v FROM level) WHERE v IS NOT NULL", 3))
def multi_query_shared(s: SparkSession, d: str) -> DataFrame:
    trees = [X.parse("SCALE(MAVG(level,10),2)"), X.parse("PLUS(SCALE(MAVG(level,10),2),MOM(level,5))")]
    return result(P.execute_many(trees, {"level": B.level(s, d)})[1], 3)


@query("interval_cover", """WITH p AS (SELECT DISTINCT o_custkey AS k, date_diff('day', TIMESTAMP '1995-01-01', o_orderdate) // 256 AS seg FROM orders),
  m AS (SELECT k, s AS seg FROM (SELECT DISTINCT k FROM p), range(10) r(s) EXCEPT SELECT k, seg FROM p)
SELECT k AS series_id, CAST(min(seg) AS BIGINT) AS seg_from, CAST(max(seg) AS BIGINT) AS seg_to FROM (SELECT k, seg, seg - row_number() OVER (PARTITION BY k ORDER BY seg) AS run FROM m) GROUP BY k, run""")
def interval_cover(s: SparkSession, d: str) -> DataFrame:
    """The segments of the whole interval in which a customer has no order."""
    import pandas as pd

    from ..plans.cache import subtract

    def missing(batches):
        for b in batches:
            rows = [(k, *gap) for k, segs in zip(b["series_id"], b["segs"], strict=True) for gap in subtract([(0, 9)], [(int(x), int(x)) for x in sorted(segs)])]
            yield pd.DataFrame(rows, columns=["series_id", "seg_from", "seg_to"])

    rows = B.read_table(s, d, "orders", ["o_custkey", "o_orderdate"]).select(F.col("o_custkey").cast("long").alias("series_id"), F.floor(B.ORDERS.index_of(F.col("o_orderdate")) / 256).alias("seg"))
    return rows.groupBy("series_id").agg(F.collect_set("seg").alias("segs")).mapInPandas(missing, "series_id long, seg_from long, seg_to long")


POS = "CAST('0x' || substr(sha1({}), 1, 8) AS BIGINT)"
RING = f"""WITH k AS (SELECT 'level#' || i AS key, {POS.format("'level#' || i")} AS pos FROM range(200) r(i)),
  n AS (SELECT 'peer' || i AS peer, {POS.format("'peer' || i")} AS place FROM range(16) r(i)),
  own AS (SELECT k.key, k.pos, coalesce((SELECT arg_min(peer, place) FROM n WHERE place >= k.pos), (SELECT arg_min(peer, place) FROM n)) AS peer FROM k)"""


def ring(s: SparkSession) -> DataFrame:
    return C.ring_assign(s.range(200).select(F.concat(F.lit("level#"), F.col("id").cast("string")).alias("key")), 16)


query("ring_assignment", f"{RING} SELECT * FROM own")(lambda s, d: ring(s))
query("ring_balance", f"{RING} SELECT peer, count(*) AS segments FROM own GROUP BY ALL")(lambda s, d: ring(s).groupBy("peer").agg(F.count(F.lit(1)).alias("segments")))
query("ring_hops")(lambda s, d: s.createDataFrame([(p, sum(C.hops(f"level#{i}", p, i) for i in range(50)) / 50) for p in (8, 32, 128)], "peers long, mean_hops double"))

TABLE = ", ".join(f"({p}, {i}, {t}, {n}, {x})" for p, i, t, n, x in C.PUBLISHED)
#: Lines of orders dealt over so many peers: look-ups, the fullest peer's lines, and all of them, in ms.
DEALT = f"""n AS (SELECT CAST(count(*) AS DOUBLE) AS n FROM lineitem), v AS (SELECT * FROM (VALUES {TABLE}) v(p, i, t, net, x)),
  l AS (SELECT p, max(k) AS load FROM (SELECT p, count(*) AS k FROM lineitem, v GROUP BY p, l_orderkey % p) GROUP BY p),
  d AS (SELECT CAST(v.p AS BIGINT) AS p, v.p * CAST(i AS DOUBLE) AS r, load * (34106.0::DOUBLE / 500000) AS t, n * (CAST(net AS DOUBLE) / 500000) AS net, CAST(x AS DOUBLE) AS x, n FROM v JOIN l USING (p), n)"""
FIT = f"""WITH {DEALT}, m AS (SELECT sum(p * log2(p) * r) / sum(pow(p * log2(p), 2)) AS b, sum(n / p * t) / sum(pow(n / p, 2)) AS a, avg(net / n) AS c, 34106.0::DOUBLE / 500000 AS k FROM d)"""


def dealt(s: SparkSession, d: str) -> DataFrame:
    return C.measured_frame(B.read_table(s, d, "lineitem", ["l_orderkey"]), "l_orderkey")


query("cost_table5", f"WITH {DEALT} SELECT p, round(r, 4) AS t_route, round(t, 4) AS t_process, round(net, 4) AS t_net, round(r + t + net, 4) AS t_total, x AS published FROM d")(
    lambda s, d: dealt(s, d).select("p", snap(F.col("p") * F.col("t_index"), 4).alias("t_route"), snap(F.col("t_process"), 4).alias("t_process"), snap(F.col("t_net"), 4).alias("t_net"), snap(F.col("p") * F.col("t_index") + F.col("t_process") + F.col("t_net"), 4).alias("t_total"), "published"))
query("cost_gain", f"WITH {DEALT} SELECT p, round((n * (34106.0::DOUBLE / 500000) + net) / (r + t + net), 4) AS gain FROM d")(
    lambda s, d: dealt(s, d).select("p", snap((F.col("n") * F.lit(C.PUBLISHED_CENTRAL / C.PUBLISHED_N) + F.col("t_net")) / (F.col("p") * F.col("t_index") + F.col("t_process") + F.col("t_net")), 4).alias("gain")))
query("cost_fit", f"{FIT} SELECT round(a, 6) AS a, round(b, 6) AS b, round(c, 6) AS c FROM m")(
    lambda s, d: (lambda m: s.createDataFrame([(m.a, m.b, m.c)], "a double, b double, c double").select(*[snap(F.col(x), 6).alias(x) for x in "abc"]))(C.measured_model(dealt(s, d))))
query("cost_gain_surface", f"{FIT} SELECT CAST(p AS BIGINT) AS p, CAST(n AS BIGINT) AS n, round(b * p * log2(p) + a * n / p + c * n, 3) AS t_total, round((k + c) * n / (b * p * log2(p) + a * n / p + c * n), 3) AS gain FROM m, (VALUES (8), (32), (64), (128), (256)) x(p), (VALUES (16000), (100000), (500000)) y(n)")(
    lambda s, d: surface(s, C.measured_model(dealt(s, d))))


def surface(s: SparkSession, m: C.Model) -> DataFrame:
    grid = s.createDataFrame([(p, n) for p in (8, 32, 64, 128, 256) for n in (16000, 100000, 500000)], "p long, n long")
    t = F.lit(m.b) * F.col("p") * F.log2("p") + F.lit(m.a) * F.col("n") / F.col("p") + F.lit(m.c) * F.col("n")
    return grid.select("p", "n", snap(t, 3).alias("t_total"), snap(F.lit(m.a_central + m.c) * F.col("n") / t, 3).alias("gain"))


@query("cost_storage", """SELECT CAST(k * years * 360 * 8.5 * 60 * 5 * 4 AS BIGINT) AS bytes, CAST(k * years * 360 * 8.5 * 60 * 5 * 4 AS BIGINT) * 50 AS copies
FROM (SELECT count(DISTINCT l_partkey) AS k, max(year(l_shipdate)) - min(year(l_shipdate)) + 1 AS years FROM lineitem)""")
def cost_storage(s: SparkSession, d: str) -> DataFrame:
    """Every part a series of minutes over the years in which lines were shipped."""
    one = C.storage_bytes(1, 1, 360, 8.5, 5, 4)
    years = F.max(F.year("l_shipdate")) - F.min(F.year("l_shipdate")) + 1
    size = B.read_table(s, d, "lineitem", ["l_partkey", "l_shipdate"]).agg((F.count_distinct("l_partkey") * years * F.lit(one)).cast("long").alias("bytes"))
    return size.select("bytes", C.replicated_bytes(F.col("bytes"), 50).alias("copies"))


query("pack_segments", f"WITH {TICKS} SELECT CAST(idx // 256 AS BIGINT) AS seg, CAST(min(idx) AS BIGINT) AS start, count(*) AS n, round(sum(v), 2) AS total FROM ticks GROUP BY ALL")(
    lambda s, d: G.pack(B.ticks(s, d), 256).select("seg", "start", F.size("vals").cast("long").alias("n"), snap(F.aggregate("vals", F.lit(0.0), lambda a, x: a + x), 2).alias("total")))
query("unpack_segments", series(LEVEL, "SELECT * FROM level"))(lambda s, d: result(G.unpack(G.pack(B.level(s, d), 256))))
