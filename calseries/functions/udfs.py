"""Functions for SQL and for Python code: on packed arrays, scalar and grouped pandas functions, table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def array_mavg(vals: Column, w: Column | int) -> Column:
    """Trailing means of an array, native."""
    w = F.lit(w) if isinstance(w, int) else w
    return F.transform(vals, lambda x, i: F.aggregate(F.slice(vals, F.greatest(F.lit(1), i + 2 - w), F.least(w, i + 1)), F.lit(0.0), lambda s, v: s + v) / F.least(w, i + 1))


def register(spark: SparkSession) -> None:
    """SQL functions ts_mavg, ts_rsi, ts_macd on arrays, and the table functions calendar_range and segment_ids."""
    spark.udf.register("ts_mavg", mavg_arrays)
    spark.udf.register("ts_macd", macd_arrays)
    spark.udf.register("ts_rsi", rsi_arrays)
    spark.udtf.register("calendar_range", CalendarRange)
    spark.udtf.register("segment_ids", SegmentIds)


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def mavg_arrays(vals: pd.Series, w: pd.Series) -> pd.Series:
    """Trailing means by running sums: the work doesn't grow with w."""

    def one(x, n):
        run = np.concatenate([[0.0], np.cumsum(np.asarray(x, float))])
        i = np.arange(1, len(run))
        lo = np.maximum(i - n, 0)
        return ((run[i] - run[lo]) / (i - lo)).tolist()

    return pd.Series([None if x is None else one(x, int(n)) for x, n in zip(vals, w, strict=True)])


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def macd_arrays(vals: pd.Series, short: pd.Series, long: pd.Series) -> pd.Series:
    x, y = mavg_arrays.func(vals, short), mavg_arrays.func(vals, long)
    return pd.Series([None if a is None else (np.array(a) - np.array(b)).tolist() for a, b in zip(x, y, strict=True)])


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def rsi_arrays(vals: pd.Series, w: pd.Series) -> pd.Series:
    def one(x, n):
        d = pd.Series(x, dtype=float).diff()
        g, l = (d.clip(lower=0).rolling(n, min_periods=1).sum(), (-d).clip(lower=0).rolling(n, min_periods=1).sum())
        return (100 * g / (g + l)).tolist()

    return pd.Series([one(x, int(n)) for x, n in zip(vals, w, strict=True)])


@F.udtf(returnType=T.StructType([T.StructField("idx", T.LongType()), T.StructField("t", T.TimestampNTZType())]))
class CalendarRange:
    """Instants from ``start`` in steps of so many seconds."""

    def eval(self, start: str, seconds: int, n: int):
        from datetime import datetime, timedelta

        at = datetime.fromisoformat(start)
        for i in range(n):
            yield i, at + timedelta(seconds=seconds * i)


@F.udtf(returnType=T.StructType([T.StructField("seg", T.LongType()), T.StructField("is_core", T.BooleanType())]))
class SegmentIds:
    """The segments whose core or halo an entry lies in."""

    def eval(self, idx: int, length: int, left: int, right: int):
        for s in range(max(0, (idx - right) // length), (idx + left) // length + 1):
            yield s, s == idx // length


@F.pandas_udf(T.DoubleType())
def clip_scale(v: pd.Series) -> pd.Series:
    """An arbitrary Python function of values, by batches: clipped to 0 … 100 and halved."""
    return v.clip(0, 100) / 2
