"""What distributing a long series over p peers costs, and the ring that places its segments."""

from __future__ import annotations

import hashlib
import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: The published run on 500,000 entries: peers, find one segment, process, ship the result, total, in ms.
PUBLISHED = [
    (8, 7.1, 4473.0, 400.0, 4930.0), (16, 6.3, 2176.0, 400.0, 2677.0), (32, 7.4, 1106.0, 400.0, 1743.0),
    (64, 8.4, 580.0, 400.0, 1518.0), (128, 8.9, 286.0, 400.0, 1825.0), (256, 9.7, 140.0, 400.0, 3023.0),
]
#: Entries and centralised processing time of that run.
PUBLISHED_N, PUBLISHED_CENTRAL = 500_000, 34_106.0


def t_route(p: float, t_index: float) -> float:
    """Finding all segments: one look-up for each of p."""
    return p * t_index


def t_total(route: float, process: float, query: float, net: float) -> float:
    return route + process + query + net


@dataclass(frozen=True)
class Model:
    """T(p, n) = b p log2 p + a n / p + c n, against a_central n + c n on one node."""

    a: float
    b: float
    c: float
    a_central: float

    def time(self, p: float, n: float) -> float:
        return self.b * p * math.log2(p) + self.a * n / p + self.c * n if p > 1 else self.a * n + self.c * n

    def gain(self, p: float, n: float) -> float:
        return (self.a_central + self.c) * n / self.time(p, n)

    def optimum(self, n: float, most: int = 4096) -> int:
        return min(range(2, most + 1), key=lambda p: self.time(p, n))


def fit(rows: list[tuple[float, float, float, float]], n: float, central: float | None = None) -> Model:
    """Least squares through the origin from (p, route, process, net) rows."""
    xs = [p * math.log2(p) for p, *_ in rows]
    ys = [n / p for p, *_ in rows]
    b = sum(x * r[1] for x, r in zip(xs, rows, strict=True)) / sum(x * x for x in xs)
    a = sum(y * r[2] for y, r in zip(ys, rows, strict=True)) / sum(y * y for y in ys)
    c = sum(r[3] for r in rows) / len(rows) / n
    return Model(a, b, c, (central / n) if central else a)


def fit_total(rows: list[tuple[float, float]], n: float) -> Model:
    """The same curve from whole times alone: non-negative a, b and c that come nearest to (p, time) rows; p above 1."""
    import itertools

    import numpy as np

    p, t = (np.array(c, float) for c in zip(*rows, strict=True))
    terms = np.stack([n / p, p * np.log2(p), np.full(len(p), float(n))], 1)
    best, loss = np.zeros(3), float((t**2).sum())
    for used in itertools.chain.from_iterable(itertools.combinations(range(3), k) for k in (1, 2, 3)):
        x = np.zeros(3)
        x[list(used)] = np.linalg.lstsq(terms[:, used], t, rcond=None)[0]
        if (x >= 0).all() and float(((terms @ x - t) ** 2).sum()) < loss:
            best, loss = x, float(((terms @ x - t) ** 2).sum())
    a, b, c = (float(v) for v in best)
    return Model(a, b, c, a)


def linearity(rows: list[tuple[float, float]]) -> dict[str, float]:
    """Slope, intercept and r2 of the least-squares line through (size, time) rows."""
    import numpy as np

    x, y = (np.array(c, float) for c in zip(*rows, strict=True))
    slope, intercept = np.polyfit(x, y, 1)
    rest = ((y - slope * x - intercept) ** 2).sum()
    total = ((y - y.mean()) ** 2).sum()
    return {"slope": float(slope), "intercept": float(intercept), "r2": float(1 - rest / total) if total else 1.0}


def published_model() -> Model:
    return fit([(p, t_route(p, one), proc, net) for p, one, proc, net, _ in PUBLISHED], PUBLISHED_N, PUBLISHED_CENTRAL)


def best_partitions(model: Model, n: int, cores: int) -> int:
    """Segments to cut a series into: the model's optimum, at least one per core."""
    return max(cores, model.optimum(n))


def storage_bytes(series: int, years: int, days: int, hours: float, fields: int, width: int) -> int:
    """Bytes of so many series of minutes."""
    return int(series * years * days * hours * 60 * fields * width)


def replicated_bytes(one_copy: int, users: int) -> int:
    """The same when every user downloads everything."""
    return one_copy * users


def published_frame(spark: SparkSession) -> DataFrame:
    rows = [(p, one, proc, net, total) for p, one, proc, net, total in PUBLISHED]
    return spark.createDataFrame(rows, "p long, t_index double, t_process double, t_net double, published double")


def measured_frame(rows: DataFrame, key: str) -> DataFrame:
    """``published_frame`` for the entries ``rows`` dealt by ``key`` over the same numbers of peers: look-ups as published,
    processing by the entries of the fullest peer, shipping by all, both at the published time an entry; and entries."""
    peers = [p for p, *_ in PUBLISHED]
    most = math.lcm(*peers)
    dealt = rows.groupBy(F.pmod(F.col(key).cast("long"), F.lit(most)).alias("k")).agg(F.count(F.lit(1)).alias("n"))
    loads = dealt.select(F.explode(F.array(*[F.lit(p) for p in peers])).alias("peers"), "k", "n").groupBy("peers", F.pmod("k", "peers").alias("k")).agg(F.sum("n").alias("n"))
    loads = loads.groupBy("peers").agg(F.max("n").alias("load"), F.sum("n").alias("n"))
    t = F.broadcast(published_frame(rows.sparkSession))  # as many rows as numbers of peers
    one, net = PUBLISHED_CENTRAL / PUBLISHED_N, F.col("t_net") / F.lit(float(PUBLISHED_N))
    return loads.join(t, F.col("peers") == F.col("p")).select("p", "t_index", (F.col("load") * F.lit(one)).alias("t_process"), (F.col("n") * net).alias("t_net"), "published", "n")


def measured_model(frame: DataFrame) -> Model:
    rows = frame.orderBy("p").collect()  # one a number of peers
    n = rows[0]["n"]
    return fit([(r["p"], t_route(r["p"], r["t_index"]), r["t_process"], r["t_net"]) for r in rows], n, n * PUBLISHED_CENTRAL / PUBLISHED_N)


def cost_table(spark: SparkSession) -> DataFrame:
    """Routing and total time by number of peers, from the published parts."""
    route = F.col("p") * F.col("t_index")
    return published_frame(spark).select("p", F.round(route, 4).alias("t_route"), "t_process", "t_net", F.round(route + F.col("t_process") + F.col("t_net"), 4).alias("t_total"), "published")


def gain_table(spark: SparkSession) -> DataFrame:
    t = cost_table(spark)
    return t.select("p", F.round((PUBLISHED_CENTRAL + F.col("t_net")) / F.col("published"), 4).alias("gain"))


def gain_surface(spark: SparkSession, peers: list[int], sizes: list[int], model: Model | None = None) -> DataFrame:
    m = model or published_model()
    grid = spark.createDataFrame([(p, n) for p in peers for n in sizes], "p long, n long")
    time = F.lit(m.b) * F.col("p") * F.log2("p") + F.lit(m.a) * F.col("n") / F.col("p") + F.lit(m.c) * F.col("n")
    return grid.select("p", "n", F.round(time, 4).alias("t_total"), F.round(F.lit(m.a_central + m.c) * F.col("n") / time, 4).alias("gain"))


# ---- ring -------------------------------------------------------------------------------------------------------------


def position(text: str, m: int = 32) -> int:
    return int(hashlib.sha1(text.encode()).hexdigest(), 16) >> (160 - m)


def ring_assign(keys: DataFrame, peers: int, m: int = 32) -> DataFrame:
    """(key, peer): the first peer at or after a key's position, round the ring; the peers' positions are a small table."""
    digits = m // 4
    spark = keys.sparkSession
    pos = lambda c: F.conv(F.substring(F.sha1(c.cast("binary")), 1, digits), 16, 10).cast("long")
    nodes = spark.range(peers).select(F.concat(F.lit("peer"), F.col("id").cast("string")).alias("peer"))
    nodes = nodes.select("peer", pos(F.col("peer")).alias("to_pos"))
    order = Window.orderBy("to_pos")
    nodes = nodes.withColumn("from_pos", F.lag("to_pos").over(order))
    top = nodes.agg(F.max("to_pos").alias("top"))
    nodes = nodes.crossJoin(top).withColumn("first", F.col("from_pos").isNull())
    k = keys.select("key", pos(F.col("key")).alias("pos"))
    inside = (F.col("pos") <= F.col("to_pos")) & (F.col("pos") > F.col("from_pos"))
    wrapped = F.col("first") & ((F.col("pos") <= F.col("to_pos")) | (F.col("pos") > F.col("top")))
    return k.join(F.broadcast(nodes), inside | wrapped).select("key", "pos", "peer")  # as many rows as peers


def hops(key: str, peers: int, start: int = 0, m: int = 32) -> int:
    """Greedy look-ups by fingers at powers of two from a peer to the owner of a key."""
    size = 1 << m
    at = sorted(position(f"peer{i}", m) for i in range(peers))
    goal = position(key, m)

    def owner(x: int) -> int:
        return next((p for p in at if p >= x % size), at[0])

    here, n, end = at[start % peers], 0, owner(goal)
    while here != end:
        ahead = (end - here) % size
        best = here
        for i in range(m):
            f = owner(here + (1 << i))
            if 0 < (f - here) % size <= ahead and (f - here) % size > (best - here) % size:
                best = f
        here, n = best, n + 1
    return n
