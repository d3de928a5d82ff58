"""Structured Streaming around series: appends to stored segments, windowed aggregates, stateful indicators, joins.

Event time must be TIMESTAMP (a zone-free one is refused by watermarks), so ``ts`` is cast; the session zone is UTC."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..calendar import Calendar
from ..series import SeriesFrame
from ..session import scratch

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, files_per_trigger: int | None = None, glob: str = "events.parquet") -> DataFrame:
    r = spark.readStream.schema(EVENTS).option("pathGlobFilter", glob)
    r = r.option("maxFilesPerTrigger", files_per_trigger) if files_per_trigger else r
    return r.parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(events: DataFrame, size: str = "1 hour", late: str | None = "2 hours") -> DataFrame:
    e = events.withWatermark("ts", late) if late and events.isStreaming else events
    return _windows(e, F.window("ts", size))


def sliding(events: DataFrame, size: str = "2 hours", step: str = "1 hour", late: str | None = "2 hours") -> DataFrame:
    e = events.withWatermark("ts", late) if late and events.isStreaming else events
    return _windows(e, F.window("ts", size, step))


def sessions(events: DataFrame, gap: str = "12 hours", late: str | None = "2 hours") -> DataFrame:
    e = events.withWatermark("ts", late) if late and events.isStreaming else events
    g = e.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return g.select("user_id", F.col("w.start").alias("start"), "n", "total")


def _windows(e: DataFrame, window: Column) -> DataFrame:
    g = e.groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return g.select(F.col("w.start").alias("start"), "event_type", "n", "total")


def deduplicated(events: DataFrame, late: str = "2 hours") -> DataFrame:
    if events.isStreaming:
        return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    return events.dropDuplicates(["event_id"])


def interval_join(left: DataFrame, right: DataFrame, within: str = "6 hours") -> DataFrame:
    """Rows of the right at most ``within`` before a left row of the same user."""
    l = left.select("user_id", F.col("ts").alias("l_ts"), F.col("event_id").alias("l_id"))
    r = right.select(F.col("user_id").alias("r_user"), F.col("ts").alias("r_ts"), F.col("event_id").alias("r_id"))
    if left.isStreaming:
        l = l.withWatermark("l_ts", "2 hours")
    if right.isStreaming:
        r = r.withWatermark("r_ts", "2 hours")
    on = (F.col("user_id") == F.col("r_user")) & (F.col("r_ts") <= F.col("l_ts")) & (F.col("r_ts") >= F.col("l_ts") - F.expr(f"INTERVAL {within}"))
    return l.join(r, on).select("user_id", "l_id", "r_id")


def dropped_late(query: StreamingQuery) -> int:
    """Rows that the watermarks of a query have dropped so far."""
    return sum(op.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for op in p["stateOperators"])


def with_dimension(events: DataFrame, dimension: DataFrame, on: str) -> DataFrame:
    return events.join(dimension, on, "left")


# ---- state ------------------------------------------------------------------------------------------------------------

STATE = "last double, n long"
OUT = "user_id long, event_id long, y double"


def recursive_average(events: DataFrame, alpha: float = 0.1) -> DataFrame:
    """y = alpha v + (1 - alpha) y per user, in order of (ts, event_id) within what arrives together."""

    def step(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last, n = state.get if state.exists else (0.0, 0)
        rows = pd.concat(list(parts)).sort_values(["ts", "event_id"])
        out = []
        for event, v in zip(rows["event_id"], rows["value"], strict=True):
            last = v if n == 0 else alpha * v + (1 - alpha) * last
            n += 1
            out.append((key[0], event, last))
        state.update((float(last), int(n)))
        yield pd.DataFrame(out, columns=["user_id", "event_id", "y"])

    return events.groupBy("user_id").applyInPandasWithState(step, OUT, STATE, "append", GroupStateTimeout.NoTimeout)


def last_w_average(events: DataFrame, w: int) -> DataFrame:
    """The mean of each user's last ``w`` values, in order of (ts, event_id) within what arrives together; the state is
    the last w - 1 values."""

    def step(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last = list(state.get[0]) if state.exists else []
        rows = pd.concat(list(parts)).sort_values(["ts", "event_id"])
        out = []
        for event, v in zip(rows["event_id"], rows["value"], strict=True):
            last = [*last, float(v)][-w:]
            out.append((key[0], event, sum(last) / len(last)))
        state.update((last[-(w - 1) :] if w > 1 else [],))
        yield pd.DataFrame(out, columns=["user_id", "event_id", "y"])

    return events.groupBy("user_id").applyInPandasWithState(step, OUT, "last array<double>", "append", GroupStateTimeout.NoTimeout)


# ---- sinks ------------------------------------------------------------------------------------------------------------


def append_series(events: DataFrame, calendar: Calendar, path: str, checkpoint: str, length: int = 1024, key: str = "event_type") -> StreamingQuery:
    """Keep the mean of each entry in stored segments: a batch rewrites the segments that it touches, whole, from sums
    and counts, so a batch that runs twice leaves the same files. What replaces them is written beside ``checkpoint``
    first, so that no file is replaced by rows that still depend on it."""

    def put(batch: DataFrame, epoch: int) -> None:
        spark = batch.sparkSession
        rows = batch.select(F.col(key).cast("string").alias("series_id"), calendar.index_of(F.col("ts")).alias("idx"), "value")
        rows = rows.groupBy("series_id", "idx").agg(F.sum("value").alias("s"), F.count("value").alias("n"))
        rows = rows.withColumn("seg", F.floor(F.col("idx") / length)).withColumn("epoch", F.lit(epoch).cast("long"))
        touched = rows.select("series_id", "seg").distinct()
        hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
        if hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(hadoop):
            old = spark.read.parquet(path).join(touched, ["series_id", "seg"], "left_semi").where(F.col("epoch") != epoch)
            rows = rows.unionByName(old.select("series_id", "idx", "s", "n", "seg", "epoch"))
        # parts of an entry stay apart by epoch: the reader adds them up
        rows = rows.select("idx", "s", "n", "epoch", "series_id", "seg")
        staged = f"{checkpoint.rstrip('/')}-staged/epoch={epoch}"
        rows.write.mode("overwrite").parquet(staged)
        done = spark.read.schema(rows.schema).parquet(staged)
        done.repartition("series_id", "seg").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("series_id", "seg").parquet(path)

    return events.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def read_appended(spark: SparkSession, path: str, calendar: Calendar) -> SeriesFrame:
    rows = spark.read.parquet(path).groupBy(F.col("series_id").cast("string").alias("series_id"), "idx").agg((F.sum("s") / F.sum("n")).alias("v"))
    return SeriesFrame(rows, calendar, "appended")


def run_once(df: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Everything there is now, written to files below the shared folder, and those read back: a folder for each batch,
    which a batch that runs twice overwrites. In mode "complete" the last one holds the result."""
    spark, schema = df.sparkSession, df.schema
    folder, epochs = scratch(spark, name), []

    def put(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/epoch={epoch}")
        epochs.append(epoch)

    w = df.writeStream.foreachBatch(put).outputMode(mode).trigger(availableNow=True)
    w = w.option("checkpointLocation", checkpoint) if checkpoint else w
    w.start().awaitTermination()
    if not epochs:
        return spark.createDataFrame([], schema)
    return spark.read.schema(schema).parquet(f"{folder}/epoch={max(epochs)}" if mode == "complete" else f"{folder}/*")
