"""Base series on the given tables, and reading and writing of series in files."""

from __future__ import annotations

import datetime as dt

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..calendar import Calendar, assign_index
from ..series import SeriesFrame

ORDERS = Calendar.regular(dt.datetime(1995, 1, 1), "day", 2405)
SHIPS = Calendar.regular(dt.datetime(1995, 1, 2), "day", 2499)
HOURS = Calendar.regular(dt.datetime(2024, 1, 1), "hour", 720)
MINUTES = Calendar.regular(dt.datetime(2024, 1, 1), "minute", 43200)
POSITIONS = Calendar.regular(dt.datetime(1970, 1, 1), "second")
TICK_ORDER = ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]


def read_table(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None, where: Column | str | None = None) -> DataFrame:
    """A table with only the columns asked for; columns and filter reach the scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.where(where) if where is not None else df
    return df.select(*cols) if cols else df


def level(spark: SparkSession, sf_dir: str) -> SeriesFrame:
    return SeriesFrame.of(read_table(spark, sf_dir, "orders", ["o_orderdate", "o_totalprice"]), None, "o_orderdate", "o_totalprice", ORDERS, "avg", "level")


def level_holes(spark: SparkSession, sf_dir: str) -> SeriesFrame:
    """``level`` with some entries made unknown and some empty."""
    a = level(spark, sf_dir)
    v = F.when(F.col("idx") % 97 == 5, F.lit(float("nan"))).when(F.col("idx") % 89 != 3, F.col("v"))
    return a.with_df(a.df.withColumn("v", v).where("v IS NOT NULL"))


def ticks(spark: SparkSession, sf_dir: str, n: int | None = None) -> SeriesFrame:
    """Prices in shipping order, numbered from 0, cut to ``n``."""
    rows = read_table(spark, sf_dir, "lineitem", [*TICK_ORDER, "l_extendedprice"])
    rows = assign_index(rows, TICK_ORDER, F.col("l_shipdate").cast("date"))
    rows = rows.where(F.col("idx") < n) if n else rows
    return SeriesFrame(rows.select(F.lit("ticks").alias("series_id"), "idx", F.col("l_extendedprice").alias("v")), POSITIONS, "ticks")


def quote_daily(spark: SparkSession, sf_dir: str) -> SeriesFrame:
    """open, high, low, close, volume per shipping day."""
    return ohlcv(read_table(spark, sf_dir, "lineitem", [*TICK_ORDER, "l_extendedprice", "l_quantity"]), "l_shipdate", "l_extendedprice", "l_quantity", SHIPS, TICK_ORDER)


def ohlcv(df: DataFrame, time: str, price: str, volume: str, calendar: Calendar, order: list[str], key: str | None = None) -> SeriesFrame:
    k = F.lit("quote") if key is None else F.col(key).cast("string")
    rows = df.select(k.alias("series_id"), calendar.index_of(F.col(time)).alias("idx"), F.col(price).alias("p"), F.col(volume).alias("q"), F.struct(*order).alias("o"))
    g = rows.groupBy("series_id", "idx").agg(F.min_by("p", "o").alias("open"), F.max("p").alias("high"), F.min("p").alias("low"), F.max_by("p", "o").alias("close"), F.sum("q").alias("volume"))
    return SeriesFrame(g, calendar, "quote")


def stock_daily(spark: SparkSession, sf_dir: str) -> SeriesFrame:
    return SeriesFrame.of(read_table(spark, sf_dir, "lineitem", ["l_partkey", "l_shipdate", "l_extendedprice"]), "l_partkey", "l_shipdate", "l_extendedprice", SHIPS, "avg", "stock")


def supplier_daily(spark: SparkSession, sf_dir: str) -> SeriesFrame:
    return SeriesFrame.of(read_table(spark, sf_dir, "lineitem", ["l_suppkey", "l_shipdate", "l_extendedprice"]), "l_suppkey", "l_shipdate", "l_extendedprice", SHIPS, "avg", "supplier")


def hourly(spark: SparkSession, sf_dir: str) -> SeriesFrame:
    return SeriesFrame.of(read_table(spark, sf_dir, "events", ["ts", "value"]), None, "ts", "value", HOURS, "avg", "hourly")


def hourly_by_type(spark: SparkSession, sf_dir: str) -> SeriesFrame:
    return SeriesFrame.of(read_table(spark, sf_dir, "events", ["ts", "value", "event_type"]), "event_type", "ts", "value", HOURS, "avg", "hourly_by_type")


def of_type(spark: SparkSession, sf_dir: str, kind: str) -> SeriesFrame:
    """The hourly series of one event type, under the common id ``e``."""
    rows = read_table(spark, sf_dir, "events", ["ts", "value"], F.col("event_type") == kind)
    return SeriesFrame.of(rows, F.lit("e"), "ts", "value", HOURS, "avg", kind)


def event_minutes(spark: SparkSession, sf_dir: str) -> SeriesFrame:
    return SeriesFrame.of(read_table(spark, sf_dir, "events", ["ts", "value"]), None, "ts", "value", MINUTES, "avg", "event_minutes")


def trips(spark: SparkSession, sf_dir: str, key: Column | None = None) -> DataFrame:
    """trip_id, t (seconds), v, gear, rpm, event_id of the events of each user, or of each value of ``key``."""
    e = read_table(spark, sf_dir, "events", ["user_id", "ts", "value", "event_type", "props", "event_id"])
    k = F.get_json_object("props", "$.k").cast("double")
    secs = F.unix_micros(F.col("ts").cast("timestamp")) / 1e6
    return e.select((F.col("user_id") if key is None else key).cast("long").alias("trip_id"), secs.alias("t"), F.col("value").alias("v"), F.col("event_type").alias("gear"), (k * 30 + 800).alias("rpm"), "event_id")


def trips8(spark: SparkSession, sf_dir: str) -> DataFrame:
    return trips(spark, sf_dir, F.pmod("user_id", F.lit(8)))


STYLES = ("normal", "nervous", "economical", "assisted")


def styles8(spark: SparkSession) -> DataFrame:
    t = F.col("id")
    names = F.array(*[F.lit(s) for s in STYLES])
    return spark.range(8).select(t.alias("trip_id"), (t % 2).alias("driver"), F.element_at(names, (F.floor(t / 2) % 4 + 1).cast("int")).alias("style"))


def null_grid(spark: SparkSession) -> DataFrame:
    """All pairs of two reals, empty and unknown."""
    four = [2.0, -1.5, None, float("nan")]
    return spark.createDataFrame([(4 * i + j, a, b) for i, a in enumerate(four) for j, b in enumerate(four)], "idx long, a double, b double")


def ramp(spark: SparkSession, n: int, kind: str = "ramp") -> SeriesFrame:
    """Generated series: a constant, a ramp, or a zigzag."""
    i = F.col("id")
    v = {"constant": F.lit(5.0), "ramp": i.cast("double"), "zigzag": F.when(i % 2 == 0, 1.0).otherwise(-1.0)}[kind]
    return SeriesFrame(spark.range(n).select(F.lit(kind).alias("series_id"), i.alias("idx"), v.alias("v")), POSITIONS, kind)


def generated(a: SeriesFrame, kind: str = "ramp") -> SeriesFrame:
    """The same kinds on the entries that ``a`` has."""
    i = F.col("idx")
    v = {"constant": F.lit(5.0), "ramp": i.cast("double"), "zigzag": F.when(i % 2 == 0, 1.0).otherwise(-1.0)}[kind]
    return a.with_df(a.df.select(F.lit(kind).alias("series_id"), "idx", v.alias("v")))


# ---- files ------------------------------------------------------------------------------------------------------------

ENTRY = T.StructType([T.StructField("series_id", T.StringType()), T.StructField("date", T.TimestampNTZType()), T.StructField("value", T.DoubleType())])
_OPTIONS = {
    "xml": {"rowTag": "timeseries", "rootTag": "document", "timestampNTZFormat": "yyyy-MM-dd'T'HH:mm:ss.SSSSSS"},
    "csv": {"header": "true", "timestampNTZFormat": "yyyy-MM-dd'T'HH:mm:ss.SSSSSS"}, "json": {"timestampNTZFormat": "yyyy-MM-dd'T'HH:mm:ss.SSSSSS"}, "orc": {}, "parquet": {},
}


def write_series(a: SeriesFrame, fmt: str, path: str) -> None:
    """(series_id, date, value): empty entries are left out, unknown ones are NaN."""
    rows = a.timed().where("v IS NOT NULL").select("series_id", F.col("t").alias("date"), F.col("v").alias("value"))
    rows.write.mode("overwrite").format(fmt).options(**_OPTIONS[fmt]).save(path)


def read_series(spark: SparkSession, fmt: str, path: str, calendar: Calendar) -> SeriesFrame:
    rows = spark.read.format(fmt).schema(ENTRY).options(**_OPTIONS[fmt]).load(path)
    return SeriesFrame(rows.select("series_id", calendar.index_of(F.col("date")).alias("idx"), F.col("value").alias("v")), calendar)


def read_jdbc(spark: SparkSession, url: str, table: str, column: str, lower, upper, parts: int) -> DataFrame:
    """A relational table in ``parts`` ranges of a column, read side by side."""
    return spark.read.format("jdbc").options(url=url, dbtable=table, partitionColumn=column, lowerBound=str(lower), upperBound=str(upper), numPartitions=str(parts)).load()


def save_bucketed(a: SeriesFrame, table: str, buckets: int, length: int = 65536) -> DataFrame:
    """A table bucketed and sorted by segment, so that windows and joins on (series_id, seg) need no shuffle."""
    rows = a.df.withColumn("seg", F.floor(F.col("idx") / length))
    rows.write.mode("overwrite").bucketBy(buckets, "series_id", "seg").sortBy("series_id", "seg", "idx").saveAsTable(table)
    return a.df.sparkSession.table(table)


def append_segments(a: SeriesFrame, path: str, length: int = 65536) -> None:
    """Replace the segments that ``a`` has rows for, and no others."""
    rows = a.df.withColumn("seg", F.floor(F.col("idx") / length))
    rows.repartition("series_id", "seg").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("series_id", "seg").parquet(path)


def register(a: SeriesFrame, view: str) -> None:
    a.timed().createOrReplaceTempView(view)
