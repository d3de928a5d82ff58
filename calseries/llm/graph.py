"""Connected components of a graph that only executors hold."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import forget, staged

#: A node with more than one in so many of all edge ends is hot.
HOT = 1000


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first())


def least(rows: DataFrame, key: str, all_values: DataFrame, count: int) -> DataFrame:
    """``rows`` with m, the least v that ``all_values`` (u, v) has for their key; ``count``: its rows, at least.

    Minima are combined before they are shuffled. A key with more than one in ``HOT`` of the values is hot; there are
    fewer than ``HOT`` of them, so their minima are broadcast and their rows stay where they are."""
    low = all_values.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("times"))
    hot = low.where(F.col("times") * HOT > count).select("u", "m")
    told = rows.join(F.broadcast(hot), F.col(key) == F.col("u"), "left").drop("u")
    cold = told.where(F.col("m").isNull()).drop("m").join(low.select("u", "m"), F.col(key) == F.col("u")).drop("u")
    return told.where(F.col("m").isNotNull()).unionByName(cold)


def components(edges: DataFrame, a: str = "a", b: str = "b", most: int = 60) -> DataFrame:
    """(node, root) for every node with an edge: root is the smallest node that edges lead to.

    Alternates two rewirings until nothing changes: every node hands its larger neighbours to its smallest one, then
    its smaller neighbours. Each keeps what is connected, and together they end in a star around each root after about
    log of the longest path. Edges from a node to itself and edges with a null end are no edges."""
    e = edges.where(F.col(a).isNotNull() & F.col(b).isNotNull() & (F.col(a) != F.col(b)))
    e = staged(e.select(F.greatest(a, b).alias("hi"), F.least(a, b).alias("lo")).distinct(), "edges")
    before = _state(e)
    if not before[0]:
        return e.select(F.col("hi").alias("node"), F.col("lo").alias("root"))
    for _ in range(most):
        both = e.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionAll(e.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        large = staged(least(e, "lo", both, 2 * before[0]).select("hi", F.least("lo", "m").alias("lo")).distinct(), "edges")
        small = least(large, "hi", large.select(F.col("hi").alias("u"), F.col("lo").alias("v")), before[0])
        pairs = F.array(F.struct(F.col("hi").alias("hi"), F.col("m").alias("lo")), F.struct(F.col("lo").alias("hi"), F.col("m").alias("lo")))
        old, e = e, staged(small.select(F.inline(pairs)).where(F.col("hi") != F.col("lo")).distinct(), "edges")
        forget(large)
        forget(old)
        after = _state(e)
        if after == before:
            return e.select(F.col("hi").alias("node"), F.col("lo").alias("root"))
        before = after
    raise RuntimeError("components did not settle")
