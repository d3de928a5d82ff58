"""Headline timings at $BENCH_SF_DIR on local[$BENCH_CPUS]: one JSON line.

The long series is read, numbered and kept in memory first, as in the published runs; every figure is the median of
``RUNS`` warm runs to a sink that keeps nothing, in seconds."""

from __future__ import annotations

import json
import os
import statistics
import sys
import time

from pyspark.sql import DataFrame, SparkSession

from calseries.baselines import ArrayEngine
from calseries.operators import window as W
from calseries.plans import cost, segments
from calseries.queries import QUERIES
from calseries.queries.windows import q1, q2, q3, q4
from calseries.session import tune
from calseries.sources.base import ramp, ticks

RUNS = int(os.environ.get("BENCH_RUNS", "2"))
SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
N = 500_000
GRID = (1000, 2000, 4000, 16_000, 100_000)
PEERS = (8, 16, 32, 64, 128, 256)
OTHERS = ["strategy_buy", "strategy_grid_topk", "eco_styles", "eco_users", "excess_over_index", "ohlc_daily", "join_asof", "join_star", "agg_basic"]


def strength(v: list[float]) -> float:
    """The generic form of the relative strength: one call a window."""
    steps = [y - x for x, y in zip(v, v[1:], strict=False)]
    gain, both = sum(d for d in steps if d > 0), sum(abs(d) for d in steps)
    return 100 * gain / both if both else float("nan")


def timed(df: DataFrame) -> float:
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def measure(make) -> dict[str, float]:
    """Median, least, most and relative spread of the warm runs of a query; ``make`` builds it anew each time."""
    timed(make())
    runs = [timed(make()) for _ in range(RUNS)]
    mid = statistics.median(runs)
    return {"median": mid, "min": min(runs), "max": max(runs), "spread": (statistics.pstdev(runs) / mid if mid else 0.0)}


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "16g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    tune(spark)
    out: dict[str, float] = {}
    spread: dict[str, float] = {}
    least: dict[str, float] = {}
    lines: dict[str, dict[str, float]] = {}

    def note(name: str, make) -> None:
        m = measure(make)
        out[name], spread[name] = round(m["median"], 4), round(m["spread"], 4)
        least[name] = round(m["min"], 4)
        print(name, out[name], file=sys.stderr, flush=True)

    a = ticks(spark, SF_DIR, N)
    n = a.df.count()
    a = a.with_df(a.df.repartition(int(CPUS)).persist())
    a.df.count()
    for w in (10, 50, 100):
        note(f"q1_w{w}", lambda w=w: q1(a, w).df)
        note(f"q2_w{w}", lambda w=w: q2(a, w).df)
        note(f"q3_w{w}", lambda w=w: q3(a, w).df)
    # the published grid of lengths
    for size in GRID:
        part = a.with_df(a.slice(0, size - 1).df.persist())
        part.df.count()
        for w in (10, 50, 100):
            for q, f in (("q1", q1), ("q2", q2), ("q3", q3)):
                note(f"{q}_n{size}_w{w}", lambda f=f, w=w: f(part, w).df)
        if size == 4000:
            note("q4_n4000", lambda: q4(segments.segment(part, 4096, 2, 0), False))
            note("rsi_selfjoin_n4000_w100", lambda: W.rsi(part, 100, "selfjoin").df)
        part.df.unpersist()
    for q in ("q1", "q2", "q3"):
        lines[f"{q}_w100_by_n"] = cost.linearity([(size, out[f"{q}_n{size}_w100"]) for size in GRID] + [(n, out[f"{q}_w100"])])
        lines[f"{q}_by_w"] = cost.linearity([(w, out[f"{q}_w{w}"]) for w in (10, 50, 100)])
    note("q4_steps", lambda: q4(segments.segment(a, 4096, 2, 0), False))
    note("q1_sliding_w100", lambda: segments.eval_segmented(a, lambda x: W.mavg(x, 100), 99, length=4096).df)
    note("q2_sliding_w100", lambda: segments.eval_segmented(a, lambda x: W.rsi(x, 100), 100, length=4096).df)
    note("q3_default_w100", lambda: W.macd(a, 3, 100, "exp").df)
    short = a.slice(0, 15_999)
    note("q3_fold_n16000_w100", lambda: segments.eval_segmented(short, lambda x: W.macd(x, 3, 100, "exp", method="fold"), 99, length=4096).df)
    note("q1_selfjoin_n16000_w100", lambda: W.mavg(short, 100, "selfjoin").df)
    note("q1_python_n16000_w100", lambda: segments.eval_segmented(short, lambda x: W.mavg(x, 100, "pandas"), 99, length=2000).df)
    note("rsi_generic_n16000_w100", lambda: segments.eval_segmented(short, lambda x: W.win_python(x, strength, 101), 100, length=2000).df)
    note("rsi_specific_n16000_w100", lambda: W.rsi(short, 100, "prefix").df)
    # the array engine, on one core and without Spark
    engine = ArrayEngine({"x": [r["v"] for r in short.df.orderBy("idx").collect()]})
    for name, run in (("mavg", lambda: engine.mavg("x", 100)), ("mavg_generic", lambda: engine.generic("x", 100, lambda v: sum(v) / len(v))), ("rsi", lambda: engine.rsi("x", 100)), ("macd", lambda: engine.macd("x", 3, 100))):
        began = time.perf_counter()
        run()
        out[f"array_{name}_n16000_w100"] = round(time.perf_counter() - began, 4)
    # a long and a short exponential average in P tasks: time falls with the parallel share and rises with the tasks
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    for p in (1, 4, *PEERS):
        spark.conf.set("spark.sql.shuffle.partitions", p)
        note(f"q3_tasks_{p}", lambda: q3(a, 100).df)
    spark.conf.set("spark.sql.shuffle.partitions", CPUS)
    spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")
    ours = cost.fit_total([(p, 1000 * out[f"q3_tasks_{p}"]) for p in PEERS], n)
    a.df.unpersist()
    long = ramp(spark, 4_000_000, "zigzag")
    note("q1_n4000000_w100", lambda: q1(long, 100).df)
    for name in OTHERS:
        note(name, lambda name=name: QUERIES[name](spark, SF_DIR))
    model = cost.published_model()
    total = sum(out.values())
    print(json.dumps({
        "metric": "seconds over all queries, warm medians", "value": round(total, 3), "unit": "sec", "queries": out, "sf": os.path.basename(SF_DIR), "n": n, "runs": RUNS, "spread": spread,
        "entries_per_sec": {k: round(n / out[k]) for k in ("q1_w100", "q2_w100", "q3_w100")}, "published_optimum_peers": model.optimum(cost.PUBLISHED_N),
        "least": least, "linear": lines, "multi_core_factor": round(out["q3_tasks_1"] / out["q3_tasks_4"], 2),
        "fitted_ms": {"a": ours.a, "b": ours.b, "c": ours.c, "optimum_tasks": ours.optimum(n)},
    }))
    spark.stop()


if __name__ == "__main__":
    sys.exit(main())
