"""Distances between series, reductions of their dimension, and small fits."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..operators.algebra import wide
from ..series import SeriesFrame, snap

# ---- distances --------------------------------------------------------------------------------------------------------


def lp(a: SeriesFrame, b: SeriesFrame, p: float = 2.0) -> DataFrame:
    """(series_id, distance) between the series of equal id; ``p`` infinity takes the largest difference."""
    d = F.abs(F.col("v0") - F.col("v1"))
    rows = wide([a, b], "inner").groupBy("series_id")
    if math.isinf(p):
        return rows.agg(F.max(d).alias("distance"))
    return rows.agg(F.pow(F.sum(F.pow(d, F.lit(float(p)))), F.lit(1.0 / p)).alias("distance"))


def array_distance(x: Column, y: Column, p: float = 2.0) -> Column:
    terms = F.zip_with(x, y, lambda a, b: F.pow(F.abs(a - b), F.lit(float(p))))
    return F.pow(F.aggregate(terms, F.lit(0.0), lambda s, t: s + t), F.lit(1.0 / p))


def dtw_arrays(x: np.ndarray, y: np.ndarray, band: int | None = None, stop: float = math.inf) -> float:
    """Dynamic time warping with absolute costs; infinite as soon as every path costs more than ``stop``."""
    n, m = len(x), len(y)
    band = max(band if band is not None else max(n, m), abs(n - m))
    prev = np.full(m + 1, math.inf)
    prev[0] = 0.0
    for i in range(1, n + 1):
        cur = np.full(m + 1, math.inf)
        lo, hi = max(1, i - band), min(m, i + band)
        cost = np.abs(x[i - 1] - y[lo - 1 : hi])
        best = np.minimum(prev[lo : hi + 1], prev[lo - 1 : hi])
        left = math.inf
        for k, (c, b) in enumerate(zip(cost.tolist(), best.tolist(), strict=True)):
            left = c + min(b, left)
            cur[lo + k] = left
        if cur.min() > stop:
            return math.inf
        prev = cur
    return float(prev[m])


def dtw_batch(x: np.ndarray, y: np.ndarray, band: int | None = None, stop: float = math.inf) -> np.ndarray:
    """The same for many pairs of rows at once: each cell of the table is worked out for all pairs."""
    k, n, m = len(x), x.shape[1], y.shape[1]
    band = max(band if band is not None else max(n, m), abs(n - m))
    prev = np.full((m + 1, k), math.inf)
    prev[0] = 0.0
    over = np.zeros(k, bool)
    for i in range(1, n + 1):
        cur = np.full((m + 1, k), math.inf)
        for j in range(max(1, i - band), min(m, i + band) + 1):
            cur[j] = np.abs(x[:, i - 1] - y[:, j - 1]) + np.minimum(np.minimum(prev[j], prev[j - 1]), cur[j - 1])
        over |= cur.min(0) > stop
        if over.all():
            break
        prev = cur
    return np.where(over, math.inf, prev[m])


def dtw(pairs: DataFrame, x: str = "x", y: str = "y", band: int | None = None, stop: float = math.inf) -> DataFrame:
    """Adds ``dtw`` to rows with two arrays: infinite where it is known to exceed ``stop``."""

    @F.pandas_udf("double")
    def one(a: pd.Series, b: pd.Series) -> pd.Series:
        sizes = pd.Series(list(zip(a.map(len), b.map(len), strict=True)), index=a.index)
        out = pd.Series(math.inf, index=a.index, dtype=float)
        for _, rows in sizes.groupby(sizes).groups.items():
            out.loc[rows] = dtw_batch(np.array(a.loc[rows].tolist(), float), np.array(b.loc[rows].tolist(), float), band, stop)
        return out

    return pairs.withColumn("dtw", one(x, y))


def lb_band(x: Column, y: Column, band: int) -> Column:
    """A lower bound of the time-warped distance of arrays of one length: how far x lies outside the band around y."""

    def outside(v: Column, i: Column) -> Column:
        near = F.slice(y, F.greatest(F.lit(1), i + 1 - band), F.lit(2 * band + 1) - F.greatest(F.lit(0), F.lit(band) - i))
        return F.greatest(v - F.array_max(near), F.array_min(near) - v, F.lit(0.0))

    return F.aggregate(F.transform(x, outside), F.lit(0.0), lambda s, t: s + t)


def dtw_block(x: np.ndarray, q: np.ndarray, band: int) -> np.ndarray:
    """Time-warped distances of the vectors in the columns of ``x`` from one vector of their length, cell by cell as
    ``dtw_batch``."""
    n, m = x.shape
    prev, cur, cost = np.full((n + 1, m), math.inf, x.dtype), np.empty((n + 1, m), x.dtype), np.empty(m, x.dtype)
    prev[0] = 0.0
    for i in range(1, n + 1):
        lo, hi = max(1, i - band), min(n, i + band)
        cur[lo - 1] = math.inf
        for j in range(lo, hi + 1):
            out = np.minimum(prev[j], prev[j - 1], out=cur[j])
            np.minimum(out, cur[j - 1], out=out)
            out += np.abs(np.subtract(x[i - 1], q[j - 1], out=cost), out=cost)
        if hi < n:
            cur[hi + 1] = math.inf
        prev, cur = cur, prev
    return prev[n]


def dtw_knn(queries: DataFrame, vectors: DataFrame, k: int, band: int, most_queries: int = 10_000) -> DataFrame:
    """(query_id, vec_id, dtw, rank): the ``k`` nearest of ``vectors`` by time-warped distance for each query row, in blocks
    of queries as ``knn``."""

    def close(x, q):
        most, width = max(np.abs(x).max(), np.abs(q).max()), 4096
        kind = np.float32 if most < 1e30 else float  # says which can be near; those are measured in full
        error = 4 * x.shape[1] * np.finfo(kind).eps
        parts = [np.ascontiguousarray(x[lo : lo + width].T.astype(kind)) for lo in range(0, len(x), width)]
        for lo in range(0, len(q), 256):
            near = []
            for r in range(lo, min(lo + 256, len(q))):
                d = np.concatenate([dtw_block(p, q[r].astype(kind), band) for p in parts])
                far = np.partition(d, k)[k] if len(d) > k else math.inf
                near.append(np.flatnonzero(d <= far * (1 + error) + error * most + 4e-6))
            at, row = np.concatenate(near), np.repeat(np.arange(lo, lo + len(near)), [len(n) for n in near])
            exact = dtw_batch(x[at], q[row], band)
            for r in range(lo, lo + len(near)):
                here = row == r
                yield r, at[here], exact[here]

    return _nearest(queries, vectors, k, most_queries, "dtw", close, lambda raw: snap(raw, 6), lambda rows: dtw(rows, "embedding", "_q", band).withColumn("dtw", snap(F.col("dtw"), 6)))


def knn(queries: DataFrame, vectors: DataFrame, k: int, most_queries: int = 10_000) -> DataFrame:
    """(query_id, vec_id, distance, rank): the ``k`` nearest of ``vectors`` (vec_id, embedding) for each query row. Any
    number of queries is worked through in blocks of about ``most_queries``, dealt by a hash of the id, each of which
    travels to every block of vectors; ties go to the smaller id.

    A matrix product says which vectors can be among the nearest; their squares are then summed as they stand."""
    d = snap(array_distance(F.col("embedding").cast("array<double>"), F.col("_q").cast("array<double>")), 6)

    def close(x, q):
        xx, qq = (x * x).sum(1), (q * q).sum(1)
        step = max(1, (1 << 22) // len(x))
        for lo in range(0, len(q), step):
            part = q[lo : lo + step]
            about = xx[None, :] + qq[lo : lo + step, None] - 2 * (part @ x.T)
            far = np.partition(about, k, 1)[:, k] if len(x) > k else np.full(len(part), math.inf)
            far = (np.sqrt(np.maximum(far, 0)) + 4e-6) ** 2 + 1e-11 * (xx.max() + qq[lo : lo + step])
            row, at = np.nonzero(about <= far[:, None])
            total = np.zeros(len(row))
            for c in range(x.shape[1]):
                total += (x[at, c] - part[row, c]) ** 2
            cut = np.searchsorted(row, np.arange(len(part) + 1))
            for r in range(len(part)):
                yield lo + r, at[cut[r] : cut[r + 1]], total[cut[r] : cut[r + 1]]

    return _nearest(queries, vectors, k, most_queries, "distance", close, lambda raw: snap(F.pow(raw, F.lit(0.5)), 6), lambda rows: rows.withColumn("distance", d))


#: Vectors that a task compares at a time.
VECTORS = 1 << 15


def _nearest(queries: DataFrame, vectors: DataFrame, k: int, most_queries: int, name: str, close, final, measured) -> DataFrame:
    """``close`` (different vectors, queries) yields for each query which vectors can be among its ``k`` nearest, and their
    raw distances, from which ``final`` makes the column ``name``.

    Vectors that are null, of another length than the rest, or hold what is no finite number go through ``measured``,
    which adds the column to rows of pairs."""
    spark, kind = vectors.sparkSession, "array<double>"
    usual = F.forall(F.col("embedding"), lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(math.inf)))
    v = vectors.select("vec_id", F.col("embedding").cast(kind).alias("embedding")).where("vec_id IS NOT NULL")
    asked = queries.select("vec_id", F.col("embedding").cast(kind).alias("embedding")).where("vec_id IS NOT NULL")
    count = asked.count()
    dim = v.agg(F.max(F.size("embedding"))).first()[0] or 0
    plain = F.coalesce((F.size("embedding") == dim) & usual, F.lit(False))
    odd = dim < 1 or v.where(~plain).unionAll(asked.where(~plain)).limit(1).count() > 0
    spread = v.where(plain).repartition(2 * spark.sparkContext.defaultParallelism, "vec_id")
    blocks = max(1, math.ceil(count / most_queries))

    def nearest(kept):
        def block(ids, rows):
            x = np.concatenate(rows)
            ids = np.concatenate(ids)
            order = np.argsort(ids, kind="stable")
            x, ids = np.ascontiguousarray(x[order]) + 0.0, ids[order]  # no negative zeros: equal vectors are equal bytes
            _, first, own = np.unique(x.view(np.dtype((np.void, x.itemsize * x.shape[1]))).ravel(), return_index=True, return_inverse=True)
            by, cut = np.argsort(own, kind="stable"), np.zeros(len(first) + 1, np.int64)
            np.cumsum(np.bincount(own.ravel(), minlength=len(first)), out=cut[1:])
            out = [[], [], []]
            q_ids, q = kept.value
            for r, at, raw in close(x[first], q):
                for u, d in zip(at.tolist(), raw.tolist(), strict=True):
                    same = ids[by[cut[u] : cut[u + 1]]]
                    near = same[:k]
                    if (near == q_ids[r]).any():
                        near = same[same != q_ids[r]][:k]
                    out[0] += [int(q_ids[r])] * len(near)
                    out[1] += near.tolist()
                    out[2] += [d] * len(near)
            return pd.DataFrame({"query_id": np.array(out[0], np.int64), "vec_id": np.array(out[1], np.int64), "raw": np.array(out[2], float)})

        def work(batches):
            ids, rows, n = [], [], 0
            for b in batches:
                if len(b):
                    ids.append(b["vec_id"].to_numpy())
                    rows.append(np.stack(b["embedding"].to_numpy()).astype(float))
                    n += len(b)
                if n >= VECTORS:
                    yield block(ids, rows)
                    ids, rows, n = [], [], 0
            if n:
                yield block(ids, rows)

        return work

    out = None
    for i in range(blocks):
        part = asked if blocks == 1 else asked.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == i)
        got = part.where(plain).toPandas()
        rows = None
        if len(got):
            kept = spark.sparkContext.broadcast((got["vec_id"].to_numpy(), np.stack(got["embedding"].to_numpy()).astype(float)))
            rows = spread.mapInPandas(nearest(kept), "query_id long, vec_id long, raw double").select("query_id", "vec_id", final(F.col("raw")).alias(name))
        if odd or rows is None:
            q = part.select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("_q"), plain.alias("_p"))
            pairs = v.withColumn("_o", plain).join(F.broadcast(q), (F.col("vec_id") != F.col("query_id")) & ~(F.col("_o") & F.col("_p")))
            pairs = measured(pairs).select("query_id", "vec_id", name)
            rows = pairs if rows is None else rows.unionAll(pairs)
        rank = F.row_number().over(Window.partitionBy("query_id").orderBy(name, "vec_id"))
        near = rows.withColumn("rank", rank).where(F.col("rank") <= k)
        out = near if out is None else out.unionAll(near)
    return out


# ---- reductions -------------------------------------------------------------------------------------------------------


def paa(a: SeriesFrame, m: int) -> SeriesFrame:
    """Means of consecutive pieces of ``m`` entries."""
    g = F.floor(F.col("idx") / m)
    return a.with_df(a.df.groupBy("series_id", g.alias("idx")).agg(F.avg("v").alias("v")))


def haar(a: SeriesFrame) -> DataFrame:
    """One level of the Haar transform: (series_id, idx, smooth, detail) of each pair of entries."""
    g = F.floor(F.col("idx") / 2)
    even, odd = F.max(F.when(F.col("idx") % 2 == 0, F.col("v"))), F.max(F.when(F.col("idx") % 2 == 1, F.col("v")))
    return a.df.groupBy("series_id", g.alias("idx")).agg(((even + odd) / F.sqrt(F.lit(2.0))).alias("smooth"), ((even - odd) / F.sqrt(F.lit(2.0))).alias("detail")).where("smooth IS NOT NULL")


def haar_levels(a: SeriesFrame, levels: int) -> DataFrame:
    """(series_id, level, idx, smooth, detail): all levels of the Haar transform by one grouping, from 1 for neighbouring
    entries; only complete blocks of 2 ** level entries have coefficients."""
    rows = a.df.where("v IS NOT NULL").withColumn("level", F.explode(F.sequence(F.lit(1), F.lit(levels))))
    size = F.pow(F.lit(2.0), F.col("level")).cast("long")
    half = F.floor(F.col("idx") / (size / 2)) % 2
    scale = F.sqrt(F.pow(F.lit(2.0), F.col("level")))
    g = rows.groupBy("series_id", "level", F.floor(F.col("idx") / size).alias("idx")).agg(
        (F.sum("v") / F.first(scale)).alias("smooth"), (F.sum(F.when(half == 0, F.col("v")).otherwise(-F.col("v"))) / F.first(scale)).alias("detail"), F.count("v").alias("_n"))
    return g.where(F.col("_n") == F.pow(F.lit(2.0), F.col("level")).cast("long")).drop("_n")


def dft(a: SeriesFrame, k: int, n: int) -> DataFrame:
    """(series_id, freq, re, im): the first ``k`` coefficients of series of ``n`` entries."""
    rows = a.df.withColumn("freq", F.explode(F.sequence(F.lit(0), F.lit(k - 1))))
    angle = F.lit(2 * math.pi / n) * F.col("freq") * F.col("idx")
    return rows.groupBy("series_id", "freq").agg(F.sum(F.col("v") * F.cos(angle)).alias("re"), F.sum(-F.col("v") * F.sin(angle)).alias("im"))


def pla(a: SeriesFrame, error: float) -> DataFrame:
    """Piecewise linear pieces by a sliding window: (series_id, first_idx, last_idx, v0, slope), each point of a piece
    within ``error`` of its line from the piece's first point. Series are read one at a time, in order."""

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("idx")
        i, v = pdf["idx"].to_numpy(float), pdf["v"].to_numpy(float)
        out, s, lo, hi = [], 0, -math.inf, math.inf
        for k in range(1, len(i) + 1):
            if k < len(i):
                d = i[k] - i[s]
                a_, b_ = max(lo, (v[k] - error - v[s]) / d), min(hi, (v[k] + error - v[s]) / d)
                if a_ <= b_:
                    lo, hi = a_, b_
                    continue
            slope = 0.0 if k - 1 == s else (lo + hi) / 2
            out.append((pdf["series_id"].iloc[0], int(i[s]), int(i[k - 1]), float(v[s]), slope))
            s, lo, hi = k, -math.inf, math.inf
        return pd.DataFrame(out, columns=["series_id", "first_idx", "last_idx", "v0", "slope"])

    return a.df.groupBy("series_id").applyInPandas(one, "series_id string, first_idx long, last_idx long, v0 double, slope double")


def svd(vectors: DataFrame, k: int, column: str = "embedding") -> DataFrame:
    """Vectors projected on the first ``k`` right singular vectors; the Gram matrix, as small as the dimension, is
    summed on the executors."""
    dim = len(vectors.select(column).first()[0])

    def products(batches):
        total = np.zeros((dim, dim))
        for b in batches:
            x = np.array(b[column].tolist(), float).reshape(-1, dim)
            total += x.T @ x
        yield pd.DataFrame({"g": [total.ravel().tolist()]})

    parts = vectors.select(column).mapInPandas(products, "g array<double>").select(F.posexplode("g").alias("at", "g")).groupBy("at").agg(F.sum("g").alias("g"))
    gram = np.zeros(dim * dim)
    for r in parts.collect():  # dim ** 2 rows
        gram[r["at"]] = r["g"]
    gram = gram.reshape(dim, dim)
    _, vec = np.linalg.eigh(gram)
    top = vec[:, ::-1][:, :k]
    parts = [F.aggregate(F.zip_with(F.col(column).cast("array<double>"), F.array(*[F.lit(float(x)) for x in top[:, c]]), lambda a, b: a * b), F.lit(0.0), lambda s, t: s + t) for c in range(k)]
    return vectors.withColumn("reduced", F.array(*parts))


# ---- fits -------------------------------------------------------------------------------------------------------------


def trend(a: SeriesFrame) -> DataFrame:
    """(series_id, slope, intercept, r2) of the least-squares line."""
    i = F.col("idx").cast("double")
    return a.df.groupBy("series_id").agg(F.regr_slope("v", i).alias("slope"), F.regr_intercept("v", i).alias("intercept"), F.regr_r2("v", i).alias("r2"))


def summary(a: SeriesFrame) -> DataFrame:
    q = [F.percentile("v", F.lit(x)).alias(f"p{int(100 * x)}") for x in (0.25, 0.5, 0.75)]
    return a.df.groupBy("series_id").agg(F.count("v").alias("n"), F.avg("v").alias("mean"), F.min("v").alias("low"), F.max("v").alias("high"), *q)


def ar1_fit(a: SeriesFrame) -> DataFrame:
    """(series_id, phi, c) of v[t] = c + phi v[t - 1], by least squares over neighbouring entries."""
    prev = F.max("v").over(Window.partitionBy("series_id").orderBy("idx").rangeBetween(-1, -1))
    rows = a.df.withColumn("p", prev).where("p IS NOT NULL")
    return rows.groupBy("series_id").agg(F.regr_slope("v", "p").alias("phi"), F.regr_intercept("v", "p").alias("c"))


def ar_fit(a: SeriesFrame, p: int) -> DataFrame:
    """(series_id, coef): intercept and ``p`` coefficients from the normal equations, summed on the executors."""
    w = Window.partitionBy("series_id").orderBy("idx")
    rows = a.df
    for k in range(1, p + 1):
        rows = rows.withColumn(f"x{k}", F.max("v").over(w.rangeBetween(-k, -k)))
    rows = rows.dropna().withColumn("x0", F.lit(1.0))
    terms = [F.sum(F.col(f"x{i}") * F.col(f"x{j}")).alias(f"g{i}_{j}") for i in range(p + 1) for j in range(i, p + 1)] + [F.sum(F.col(f"x{i}") * F.col("v")).alias(f"y{i}") for i in range(p + 1)]

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        out = []
        for r in pdf.to_dict("records"):
            g = np.array([[r[f"g{min(i, j)}_{max(i, j)}"] for j in range(p + 1)] for i in range(p + 1)], float)
            y = np.array([r[f"y{i}"] for i in range(p + 1)], float)
            out.append((r["series_id"], np.linalg.lstsq(g, y, rcond=None)[0].tolist()))
        return pd.DataFrame(out, columns=["series_id", "coef"])

    return rows.groupBy("series_id").agg(*terms).mapInPandas(lambda it: (solve(x) for x in it), "series_id string, coef array<double>")


def ar_forecast(a: SeriesFrame, coef: DataFrame, horizon: int) -> DataFrame:
    """(series_id, idx, v): the next entries after the last, by the fitted recursion."""
    last = a.df.groupBy("series_id").agg(F.max("idx").alias("e"))
    near = a.df.join(last, "series_id").join(coef, "series_id").where(F.col("idx") > F.col("e") - F.size("coef") + 1)
    g = near.groupBy("series_id", "e", "coef").agg(F.reverse(F.transform(F.sort_array(F.collect_list(F.struct("idx", "v"))), lambda x: x["v"])).alias("past"))

    def go(acc, _):
        new = F.aggregate(F.zip_with(F.slice("coef", F.lit(2), F.size("coef") - 1), F.slice(acc, F.lit(1), F.size("coef") - 1), lambda c, x: c * F.coalesce(x, F.lit(0.0))), F.element_at("coef", 1), lambda s, t: s + t)
        return F.concat(F.array(new), acc)

    done = g.withColumn("all", F.aggregate(F.sequence(F.lit(1), F.lit(horizon)), F.col("past"), go))
    ahead = done.select("series_id", "e", F.posexplode(F.reverse(F.slice("all", F.lit(1), F.lit(horizon)))).alias("k", "v"))
    return ahead.select("series_id", (F.col("e") + 1 + F.col("k")).alias("idx"), "v")
