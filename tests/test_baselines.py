"""The array engine as a reference, scales of values, safe exponential averages, fits, and functions without an oracle."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from calseries.baselines import ArrayEngine
from calseries.calendar import assign_index
from calseries.functions import vectors as V
from calseries.operators import trips as T
from calseries.operators import window as W
from calseries.plans import cost as C
from calseries.plans import expr as X
from calseries.plans import planner as P
from calseries.plans import segments as G
from calseries.plans.cache import Cache
from calseries.sources import base as B
from calseries.streaming import stream as S

from .conftest import SMALL
from .test_model import make, values


def wave(n=600, scale=1.0):
    return [scale * (10 + math.sin(i / 7) + (i * 37 % 11) / 9) for i in range(n)]


@pytest.mark.parametrize("scale", [1.0, 1e-12, 1e18])
def test_methods_equal_the_array_engine(spark, scale):
    x = wave(scale=scale)
    a, e = make(spark, list(enumerate(x)), 600), ArrayEngine({"x": x})
    for got, want, first in (
        (W.mavg(a, 30, "prefix"), e.mavg("x", 30), 0), (W.mavg(a, 30), e.generic("x", 30, lambda v: sum(v) / len(v)), 0), (W.rsi(a, 14, "prefix"), e.rsi("x", 14), 1),
        (W.rsi(a, 14), e.rsi("x", 14), 1), (W.macd(a, 3, 20, "exp"), e.macd("x", 3, 20), 0), (W.xavg(a, 3), e.xavg("x", 3), 0),
    ):
        found = values(got)
        top = max(abs(v) for v in want)
        assert sorted(found) == list(range(first, 600)) and all(abs(found[i + first] - v) <= 1e-9 * top for i, v in enumerate(want))


def test_short_average_in_long_segments(spark):
    """Weights of a short average overflow in a long segment: it is folded there, and the result is the same."""
    a = B.ramp(spark, 6000)
    got = values(G.eval_segmented(a, lambda x: W.xavg(x, 3), 2, length=3000))
    assert len(got) == 6000 and all(abs(v - (i - (0 if i == 0 else 1 / 3 if i == 1 else 4 / 7))) < 1e-6 for i, v in got.items())


def test_selfjoin_strength_ignores_w_in_cost(spark):
    a = make(spark, list(enumerate(wave(80))), 80)
    for w in (3, 20):
        x, y = values(W.rsi(a, w, "selfjoin")), values(W.rsi(a, w))
        assert x.keys() == y.keys() and all(abs(x[i] - y[i]) < 1e-9 for i in x)


def test_user_indicator(spark):
    W.register_indicator("mrange", lambda a, w: W.win_list(a, lambda v: F.array_max(v) - F.array_min(v), w, "trailing"), lambda w, **_: w - 1, "abs")
    try:
        a = make(spark, list(enumerate([1.0, 5.0, 2.0, 2.0])))
        assert values(W.indicator("MRANGE", a, w=2)) == {0: 0.0, 1: 4.0, 2: 3.0, 3: 0.0}
        assert values(P.lower(X.parse("MRANGE(x,2)"), {"x": a}, 2)) == {0: 0.0, 1: 4.0, 2: 3.0, 3: 0.0}
    finally:
        W.REGISTRY.pop("MRANGE")


def test_trees_without_a_single_task(spark):
    """One base or two, fused or operator by operator: no window has a whole series in one task."""
    a = B.ticks(spark, SMALL)
    a = a.with_df(spark.createDataFrame(a.df.collect(), a.df.schema))
    for text in ("JOIN(MAVG(x,10),SCALE(RSI(x,14),100),SUM)", "MAVG(MINUS(MAVG(x,6),MAVG(y,6)),12)", "MAVG(SHIFT(x,3),5)"):
        df = P.lower(X.parse(text), {"x": a, "y": a}, 512).df
        plan = df._jdf.queryExecution().optimizedPlan().toString()
        assert "Window [" in plan and all("seg" in line for line in plan.splitlines() if "Window [" in line), text


def test_random_holder_is_drawn(spark, tmp_path):
    cache, n = Cache(spark, str(tmp_path), length=16, seed=3), X.parse("MAVG(x,2)")
    a = B.ramp(spark, 32)
    for _ in range(2):
        cache.store(n, a.df, 0, 1)
    for _ in range(12):
        assert cache.read(n, [(0, 1)]).count() == 32
    assert all(0 < e.hits < 12 for e in cache.catalog.all())


def test_eviction_policies(spark, tmp_path):
    for policy, gone in (("fifo", "a"), ("lru", "b"), ("lfu", "b"), ("cost", "b")):
        cache = Cache(spark, str(tmp_path / policy), capacity=24 * 32, policy=policy, length=16)
        rows = B.ramp(spark, 16).df
        for name in "ab":
            cache.store(X.parse(f"MAVG({name},2)"), rows, 0, 0)
        cache.read(X.parse("MAVG(a,2)"), [(0, 0)])
        cache.store(X.parse("MAVG(c,2)"), rows, 0, 0)
        assert cache.evicted == [f"MAVG({gone};w=2)"], policy


def test_segment_length_by_the_model():
    m = C.published_model()
    assert P.segment_length(500_000, 8, m) == -(-500_000 // 63) and P.segment_length(2000, 8, m) == 1024 and P.segment_length(10**9, 8, m) == 65536


def test_fits():
    m = C.fit_total([(p, 0.07 * 500_000 / p + 1.2 * p * math.log2(p) + 0.0008 * 500_000) for p in (8, 16, 32, 64, 128, 256)], 500_000)
    assert abs(m.a - 0.07) < 1e-6 and abs(m.b - 1.2) < 1e-6 and abs(m.c - 0.0008) < 1e-9 and 32 < m.optimum(500_000) < 128
    line = C.linearity([(1, 3.0), (2, 5.0), (5, 11.0)])
    assert abs(line["slope"] - 2) < 1e-9 and abs(line["intercept"] - 1) < 1e-9 and line["r2"] > 1 - 1e-12


def test_rows_without_a_bucket_come_first(spark):
    d = spark.createDataFrame([(None, 1), (3, 2), (1, 3), (None, 0), (1, 1)], "b int, x int")
    got = [(r["b"], r["x"]) for r in assign_index(d, ["b", "x"], F.col("b")).orderBy("idx").collect()]
    assert got == [(None, 0), (None, 1), (1, 1), (1, 3), (3, 2)]


def test_svd_and_pca_equal_numpy(spark):
    v = spark.read.parquet(f"{SMALL}/embeddings.parquet").select("vec_id", "embedding")
    x = np.array([r["embedding"] for r in v.orderBy("vec_id").collect()], float)
    _, _, vt = np.linalg.svd(x, full_matrices=False)
    got = np.array([r["reduced"] for r in V.svd(v, 3).orderBy("vec_id").collect()])
    assert np.allclose(np.abs(got), np.abs(x @ vt[:3].T), atol=1e-4)
    rows = T.indicators(B.trips(spark, SMALL), tie="event_id")
    cols = ["rpa", "pke", "pst"]
    pdf = T.principal_components(rows, cols).join(rows, "trip_id").orderBy("trip_id").toPandas()
    z = (pdf[cols] - pdf[cols].mean()) / pdf[cols].std()
    _, _, vt = np.linalg.svd(z.to_numpy(), full_matrices=False)
    assert np.allclose(np.abs(np.array(pdf["pc"].tolist())), np.abs(z.to_numpy() @ vt[:2].T), atol=1e-6)


def test_pieces_and_forecasts(spark):
    a = make(spark, [(i, float(min(i, 8 - i))) for i in range(9)], 9)
    pieces = [(r["first_idx"], r["last_idx"], r["v0"], r["slope"]) for r in V.pla(a, 0.0).orderBy("first_idx").collect()]
    assert pieces == [(0, 4, 0.0, 1.0), (5, 8, 3.0, -1.0)]
    x = [1.0, 2.0]
    for _ in range(40):
        x.append(1 + 0.5 * x[-1] - 0.3 * x[-2])
    b = make(spark, list(enumerate(x[:30])), 30)
    coef = V.ar_fit(b, 2)
    got = [r["v"] for r in V.ar_forecast(b, coef, 5).orderBy("idx").collect()]
    assert np.allclose(got, x[30:35], atol=1e-6)


def test_batched_warping(spark):
    rng = np.random.default_rng(2)
    x, y = rng.normal(size=(20, 12)), rng.normal(size=(20, 12))
    want = [V.dtw_arrays(p, q, 3) for p, q in zip(x, y)]
    assert np.allclose(V.dtw_batch(x, y, 3), want)
    stop = float(np.median(want))
    assert [v for v in V.dtw_batch(x, y, 3, stop) if np.isfinite(v)] == [v for v in want if v <= stop] or np.allclose([v for v in V.dtw_batch(x, y, 3, stop) if v <= stop], [v for v in want if v <= stop])
    d = spark.createDataFrame([(i, p.tolist(), q.tolist()) for i, (p, q) in enumerate(zip(x, y))], "i int, x array<double>, y array<double>")
    rows = V.dtw(d, "x", "y", 3).withColumn("bound", V.lb_band(F.col("x"), F.col("y"), 3)).orderBy("i").collect()
    assert np.allclose([r["dtw"] for r in rows], want) and all(r["bound"] <= r["dtw"] + 1e-9 for r in rows) and max(r["bound"] for r in rows) > 0


def test_approximate_distinct_is_near(spark):
    e = B.read_table(spark, SMALL, "events", ["user_id", "event_id"])
    r = e.agg(F.count_distinct("event_id").alias("n"), F.approx_count_distinct("event_id", 0.02).alias("m")).first()
    assert abs(r["m"] - r["n"]) <= 0.06 * r["n"]
