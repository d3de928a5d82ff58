"""Trees, rewriting, segments, cache and cost model."""

import itertools
import random

import pytest

from calseries.operators import window as W
from calseries.plans import cost as C
from calseries.plans import expr as X
from calseries.plans import planner as P
from calseries.plans import segments as G
from calseries.plans.cache import Cache, Catalog, Entry, intersect, merge, subtract
from calseries.plans.rewrite import canonical
from calseries.sources import base as B

from .conftest import SMALL

TREE = "JOIN(MAVG(level,10),SCALE(RSI(level,14),100),SUM)"
BUY = "SEL(MAVG(MINUS(MAVG(level,12),MAVG(level,26)),9),gt,0)"


def rows(sf):
    return {(r["series_id"], r["idx"]): round(r["v"], 6) for r in sf.df.where("NOT isnan(v)").collect()}


def test_names_parse_back():
    for t in (TREE, BUY, "DIVIDE(MAVG(level,26),MAVG(level,12))", "SHIFT(level,3)"):
        n = X.parse(t)
        assert X.parse(X.name(n)) == n


def test_scale_and_momentum_commute():
    a, b = (canonical(X.parse(t)) for t in ("SCALE(MOM(level,5),100)", "MOM(SCALE(level,100),5)"))
    assert X.key(a) == X.key(b)
    assert canonical(X.parse("RSI(SCALE(level,3),14)")) == X.parse("RSI(level,14)")
    assert canonical(X.parse("MINUS(level,level)")) == canonical(X.parse("SCALE(level,0)"))


def random_tree(rng, depth=3):
    if depth == 0:
        return X.Node.base(rng.choice("xyz"))
    kind = rng.randrange(5)
    a = random_tree(rng, depth - 1)
    if kind < 2:
        return (a + random_tree(rng, depth - 1)) if kind else (a - random_tree(rng, depth - 1))
    if kind == 2:
        return a * rng.choice([1.0, 2.0, -1.0, 0.5])
    return a.window("MAVG", w=rng.choice([3, 5])) if kind == 3 else a.window("MOM", k=2)


def test_canonical_settles_and_ignores_order():
    rng = random.Random(4)
    for _ in range(300):
        t = random_tree(rng)
        c = canonical(t)
        assert canonical(c) == c
    x, y, z = (X.Node.base(c) for c in "xyz")
    assert len({X.name(canonical(a + (b + c))) for a, b, c in itertools.permutations((x, y, z))}) == 1


def test_halo_adds_up():
    assert X.halo(X.parse(BUY)) == (33, 0)
    assert X.halo(X.parse("SHIFT(level,-4)")) == (0, 4)
    assert [X.name(n) for n in X.decompose(X.parse("PLUS(MAVG(a,3),MOM(b,2))"))] == ["MAVG(a;w=3)", "MOM(b;k=2)"]


@pytest.mark.parametrize("length,left,right", [(64, 33, 0), (16, 33, 0), (1024, 128, 128)])
def test_segmented_equals_global(spark, length, left, right):
    a, tree = B.level(spark, SMALL), X.parse(BUY)
    got = G.core(P.fuse(tree, G.segment(a, length, left, right)))
    assert rows(got) == rows(P.evaluate(tree, {"level": a}))


def test_too_small_a_halo_is_wrong(spark):
    a, tree = B.level(spark, SMALL), X.parse(BUY)
    assert rows(G.core(P.fuse(tree, G.segment(a, 64, 8, 0)))) != rows(P.evaluate(tree, {"level": a}))


def test_segmented_plan_has_no_single_task_and_one_shuffle(spark):
    a = B.ticks(spark, SMALL)
    a = a.with_df(spark.createDataFrame(a.df.collect(), a.df.schema))
    plan = P.lower(X.parse("SEL(MAVG(MINUS(MAVG(ticks,12),MAVG(ticks,26)),9),gt,0)"), {"ticks": a}, 1024).df._jdf.queryExecution().executedPlan().toString()
    assert "SinglePartition" not in plan and plan.count("Exchange") == 1 and "Join" not in plan


def test_interval_reaches_the_scan(spark):
    from calseries.series import SeriesFrame

    path = "/tmp/calseries-test-scan"
    B.level(spark, SMALL).df.write.mode("overwrite").parquet(path)
    a = SeriesFrame(spark.read.parquet(path), B.ORDERS)
    plan = P.lower(X.parse("MAVG(level,10)"), {"level": a}, 256, (500, 600)).df._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThanOrEqual(idx,491)" in plan and "LessThanOrEqual(idx,600)" in plan


def test_ranges():
    assert merge([(5, 7), (0, 2), (3, 4)]) == [(0, 7)]
    assert subtract([(0, 9)], [(2, 3), (8, 12)]) == [(0, 1), (4, 7)]
    assert intersect([(0, 4), (8, 9)], [(3, 8)]) == [(3, 4), (8, 8)]


def store(cache, text, a, b):
    n = X.parse(text)
    cache.catalog.put(Entry(X.key(n), X.name(n), "", a, b, 1, 1))


@pytest.mark.parametrize("order", ["top_down", "bottom_up"])
def test_annotation(spark, order):
    tree, cache = X.parse(TREE), Cache(spark, "/tmp/none", length=512)
    kinds = lambda: [(n, k) for n, k, _ in P.scans(P.annotate(tree, [(0, 2)], cache, 512, order))]
    assert [k for _, k in kinds()] == ["computed", "computed", "base", "computed", "computed", "base"]
    store(cache, "MAVG(level,10)", 0, 2)
    store(cache, "SCALE(RSI(level,14),100)", 0, 2)
    assert kinds() == [(X.name(tree), "computed"), ("MAVG(level;w=10)", "stored"), ("SCALE(RSI(level;w=14);s=100)", "stored")]
    store(cache, TREE, 0, 2)
    assert kinds() == [(X.name(tree), "stored")]


def test_partial_annotation_widens_by_the_halo(spark):
    cache = Cache(spark, "/tmp/none", length=512)
    store(cache, "MAVG(level,10)", 0, 1)
    a = P.annotate(X.parse("MAVG(level,10)"), [(0, 2)], cache, 512)
    assert a.cached == [(0, 1)] and a.compute == [(2, 2)] and a.children[0].compute == [(1, 2)]


def test_cached_equals_cold_and_eviction(spark, tmp_path):
    bases, tree = {"level": B.level(spark, SMALL)}, X.parse(TREE)
    cold = rows(P.execute(tree, bases, [(0, 4)], None, 512))
    cache = Cache(spark, str(tmp_path), length=512)
    P.execute(tree.children[0], bases, [(0, 1)], cache, 512, keep=True)
    assert rows(P.execute(tree, bases, [(0, 4)], cache, 512, keep=True)) == cold
    assert rows(P.execute(tree, bases, [(0, 4)], cache, 512)) == cold and cache.stats()["segment_hits"] > 0
    assert cache.invalidate("level", [(4, 4)]) == 1
    small = Cache(spark, str(tmp_path / "b"), capacity=1, policy="fifo", length=512)
    P.execute(tree.children[0], bases, [(0, 0)], small, 512, keep=True)
    P.execute(tree.children[1], bases, [(0, 0)], small, 512, keep=True)
    assert small.evicted == ["MAVG(level;w=10)"]
    assert Catalog().lookup("x") == []


def test_published_cost_arithmetic():
    for p, one, process, net, total in C.PUBLISHED:
        assert abs(C.t_total(C.t_route(p, one), process, 0, net) - total) <= 1
    m = C.published_model()
    assert 32 < m.optimum(C.PUBLISHED_N) < 128 and m.optimum(C.PUBLISHED_N) == 63
    assert abs(m.b - 1.2287) < 1e-3 and abs(m.a - 0.071204) < 1e-5
    gains = [m.gain(p, C.PUBLISHED_N) for p in (8, 63, 256)]
    assert gains[1] > gains[0] and gains[1] > gains[2]
    assert C.storage_bytes(1000, 10, 360, 8.5, 5, 4) == 36_720_000_000


def test_ring_hops_grow_slowly():
    mean = lambda p: sum(C.hops(f"k{i}", p, i) for i in range(60)) / 60
    assert mean(8) < mean(128) < 9


def test_recursive_average_equals_a_loop(spark):
    a = B.level(spark, SMALL)
    data = sorted((r["idx"], r["v"]) for r in a.df.collect())
    y, want = None, {}
    for i, v in data:
        y = v if y is None else 0.1 * v + 0.9 * y
        want[i] = y
    got = {r["idx"]: r["v"] for r in G.xavg_recursive(a, 0.1, 64).df.collect()}
    assert got.keys() == want.keys() and max(abs(got[i] - want[i]) for i in want) < 1e-6


def test_methods_agree_on_the_long_series(spark):
    a = B.ticks(spark, SMALL)
    x = rows(W.xavg(a, 20))
    y = rows(G.eval_segmented(a, lambda s: W.xavg(s, 20, method="prefix"), 19, length=256))
    assert x.keys() == y.keys() and max(abs(x[k] - y[k]) for k in x) < 1e-4


def test_dtw():
    import numpy as np

    from calseries.functions.vectors import dtw_arrays

    rng = np.random.default_rng(1)
    x, y = rng.normal(size=12), rng.normal(size=9)
    full = np.full((13, 10), np.inf)
    full[0, 0] = 0
    for i in range(1, 13):
        for j in range(1, 10):
            full[i, j] = abs(x[i - 1] - y[j - 1]) + min(full[i - 1, j], full[i, j - 1], full[i - 1, j - 1])
    assert abs(dtw_arrays(x, y) - full[12, 9]) < 1e-12 and dtw_arrays(x, x, 2) == 0


def test_knn_takes_more_queries_than_a_block(spark):
    from pyspark.sql import functions as F

    from calseries.functions.vectors import knn

    v = spark.range(40).select(F.col("id").alias("vec_id"), F.array(F.col("id") % 7, F.col("id") * 0.5).alias("embedding"))
    want, got = (sorted(tuple(r) for r in knn(v, v, 3, most).collect()) for most in (10_000, 15))
    assert len(want) == 120 and got == want


def test_nearest_equal_all_pairs(spark, monkeypatch):
    """Copies, ties, repeated ids, several chunks and vectors of odd forms; and nothing is measured pair by pair in rows."""
    import collections

    import numpy as np
    from pyspark.sql import functions as F

    from calseries.functions import vectors as V

    monkeypatch.setattr(V, "VECTORS", 20)
    rng = np.random.default_rng(3)
    rows = [(i, rng.normal(size=6).round(1).tolist()) for i in range(70)]
    rows += [(100 + i, list(rows[i % 3][1])) for i in range(30)] + [(5, [0.0] * 6), (6, [-0.0] * 6)]
    pick = "vec_id % 7 < 2"
    for more in ([], [(300, [1.0, 2.0]), (301, [float("inf"), 0.0, 0.0, 0.0, 0.0, 0.0])]):
        v = spark.createDataFrame(rows + more, "vec_id long, embedding array<float>")
        exact = {}
        for name, d in (("distance", V.array_distance(F.col("embedding").cast("array<double>"), F.col("_q").cast("array<double>"))), ("dtw", None)):
            pairs = v.join(v.where(pick).select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("_q")), F.col("vec_id") != F.col("query_id"))
            pairs = (V.dtw(pairs, "embedding", "_q", 2) if d is None else pairs.withColumn(name, d)).withColumn(name, V.snap(F.col(name), 6))
            by = collections.defaultdict(list)
            for r in pairs.select("query_id", name, "vec_id").collect():
                by[r["query_id"]].append((r[name] is not None, r[name] or 0, r["vec_id"]))
            exact[name] = sorted((q, x[2], i + 1) for q, xs in by.items() for i, x in enumerate(sorted(xs)[:4]))
        got = {"distance": V.knn(v.where(pick), v, 4), "dtw": V.dtw_knn(v.where(pick), v, 4, 2)}
        for name, df in got.items():
            assert sorted((r["query_id"], r["vec_id"], r["rank"]) for r in df.collect()) == exact[name]
            assert more or "Join" not in df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", ["calendar_regular", "gen_ramp", "interval_cover", "cost_table5", "cost_gain", "cost_fit", "cost_gain_surface", "cost_storage"])
def test_queries_read_a_given_table(spark, monkeypatch, name):
    from calseries.queries import QUERIES

    read, kept = [], B.read_table
    monkeypatch.setattr(B, "read_table", lambda *a: read.append(a[2]) or kept(*a))
    assert QUERIES[name](spark, SMALL).count() > 0 and read and set(read) <= {"events", "orders", "lineitem"}
