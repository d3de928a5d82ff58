"""From a tree to a DataFrame: annotate with what is stored, prune, fuse, and evaluate the rest by segments."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .. import nulls
from ..operators import algebra, window
from ..series import SeriesFrame
from .cache import Cache, Ranges, intersect, merge, size, subtract
from .cost import PUBLISHED_N, Model, best_partitions, published_model
from .expr import Node, halo, name, reach, walk
from .rewrite import canonical, shared
from .segments import core, eval_segmented, segment

TESTS = {">": lambda v, c: v > c, "<": lambda v, c: v < c, "gt": lambda v, c: v > c, "ge": lambda v, c: v >= c, "lt": lambda v, c: v < c, "le": lambda v, c: v <= c}


@dataclass
class Annotated:
    """A node with the segments to read from the store, those to compute, and what that needs of its children."""

    node: Node
    cached: Ranges
    compute: Ranges
    children: list[Annotated] = field(default_factory=list)

    @property
    def pruned(self) -> bool:
        return not self.compute


def widen(r: Ranges, n: Node, length: int) -> Ranges:
    left, right = reach(n)
    return merge((max(0, a - -(-left // length)), b + -(-right // length)) for a, b in r)


def annotate(n: Node, want: Ranges, cache: Cache | None, length: int = 1024, order: str = "top_down") -> Annotated:
    """Ask the directory what is stored. ``top_down`` asks the root first and descends only where segments miss;
    ``bottom_up`` asks every node and then prunes: the same tree, more look-ups."""
    if order == "bottom_up" and cache is not None:
        known = {name(x): cache.catalog.cover(x) for x in walk(n)}
        cache.counts["lookups"] += len(known) * size(want)
        return _annotate(n, want, lambda x: known[name(x)], cache, length, count=False)
    return _annotate(n, want, cache.catalog.cover if cache else (lambda x: []), cache, length)


def _annotate(n: Node, want: Ranges, cover, cache: Cache | None, length: int, count: bool = True) -> Annotated:
    want = merge(want)
    have = intersect(want, cover(n)) if want else []
    need = subtract(want, have)
    if cache is not None:
        cache.counts["lookups"] += size(want) * count
        cache.counts["segments_wanted"] += size(want)
        cache.counts["segment_hits"] += size(have)
    kids = [_annotate(c, widen(need, n, length), cover, cache, length, count) for c in n.children] if need else []
    return Annotated(n, have, need, kids)


def scans(a: Annotated) -> list[tuple[str, str, Ranges]]:
    """What a pruned tree does, as (name, "stored" | "base" | "computed", segments)."""
    out = [(name(a.node), "stored", a.cached)] if a.cached else []
    if a.compute:
        out.append((name(a.node), "base" if a.node.op == "BASE" else "computed", a.compute))
    return out + [x for c in a.children for x in scans(c)]


# ---- evaluation -------------------------------------------------------------------------------------------------------


def apply(n: Node, kids: list[SeriesFrame]) -> SeriesFrame:
    """One operator on evaluated children."""
    p = dict(n.params)
    if n.op == "PLUS":
        return algebra.join(kids, "SUM")
    if n.op == "MINUS":
        return algebra.minus(*kids)
    if n.op == "MULT":
        return algebra.join(kids, "PRODUCT")
    if n.op == "DIVIDE":
        return algebra.ratio(*kids)
    if n.op == "SCALE":
        return algebra.scale(kids[0], p["s"])
    if n.op == "SHIFT":
        return algebra.shift(kids[0], int(p.get("k", 1)))
    if n.op == "JOIN":
        return algebra.join(kids, str(p.get("fn", "SUM")))
    if n.op == "SEL":
        return algebra.select(kids[0], lambda v: TESTS[str(p["test"])](v, F.lit(float(p["value"]))))
    if n.op in window.REGISTRY:
        return window.indicator(n.op, kids[0], **p)
    raise ValueError(f"unknown operator: {n.op}")


#: Parameters that make a window depend on where the series starts, or on the method: it can't be cut into segments.
WHOLE = {"frame", "border", "method"}


def evaluate(n: Node, bases: dict[str, SeriesFrame], memo: dict[str, SeriesFrame] | None = None, length: int | None = None) -> SeriesFrame:
    """The whole tree, one operator after the other; with ``length`` every window runs inside segments of that many
    entries, so that no task has a whole series."""
    memo = {} if memo is None else memo
    k = name(n)
    if k not in memo:
        memo[k] = bases[str(n.param("name"))] if n.op == "BASE" else apply_cut(n, [evaluate(c, bases, memo, length) for c in n.children], length)
    return memo[k]


def apply_cut(n: Node, kids: list[SeriesFrame], length: int | None) -> SeriesFrame:
    """One operator on evaluated children, a window inside segments with the halo that it reaches."""
    if length is None or n.op not in window.REGISTRY or WHOLE & {k for k, _ in n.params}:
        return apply(n, kids)
    return eval_segmented(kids[0], lambda x: apply(n, [x]), *reach(n), length=length)


def fuse(n: Node, sf: SeriesFrame, at: dict[str, str] | None = None) -> SeriesFrame:
    """A tree in one frame: every node is a column, no node is a join. ``at`` names the column of each base series; a
    single one is ``v``.

    Nodes that are equal in canonical form are one column. Windows over the base itself share one ordering; a window
    over a computed node opens another on the same key."""
    cols: dict[str, str] = {}
    df = sf.df.withColumns({f"b_{c}": F.col(c) for c in (at or {"": "v"}).values()})

    def column(x: Node) -> str:
        nonlocal df
        k = name(canonical(x))
        if k in cols:
            return cols[k]
        if x.op == "BASE":
            cols[k] = f"b_{at[str(x.param('name'))] if at else 'v'}"
            return cols[k]
        kids = [column(c) for c in x.children]
        out = f"c{len(cols) + 1}"
        v = [F.col(c) for c in kids]
        p = dict(x.params)
        if x.op in ("PLUS", "MULT", "MINUS", "DIVIDE") or (x.op == "JOIN"):
            f = {"PLUS": algebra.FUNCTIONS["SUM"], "MULT": algebra.FUNCTIONS["PRODUCT"], "MINUS": lambda a, b: a - b, "DIVIDE": nulls.divide}.get(x.op) or algebra.FUNCTIONS[str(p.get("fn", "SUM"))]
            df = df.withColumn(out, nulls.lift(f, *v))
        elif x.op == "SCALE":
            df = df.withColumn(out, v[0] * F.lit(float(p["s"])))
        elif x.op == "SEL":
            keep = nulls.known(TESTS[str(p["test"])](v[0], F.lit(float(p["value"]))), v[0])
            df = df.withColumn(out, F.when(keep | nulls.is_unknown(v[0]), v[0]))
        else:
            df = df.withColumn("v", v[0])  # window columns read v
            if x.op == "RSI":
                df = df.withColumn("_d", F.col("v") - window.back(sf.with_df(df), 1))
            df = df.withColumn(out, window_column(x, sf.with_df(df)))
        cols[k] = out
        return out

    top = column(n)
    keep = [c for c in ("series_id", "seg", "seg_at", "is_core", "idx") if c in sf.df.columns]
    return sf.with_df(df.select(*keep, F.col(top).alias("v")).where("v IS NOT NULL"))


def window_column(n: Node, a: SeriesFrame) -> Column:
    """The window operators that fit in a column of the frame they read; entries that are empty stay out of it."""
    p, v = dict(n.params), F.col("v")
    on = lambda c: F.when(v.isNotNull(), c)
    if n.op == "MAVG":
        return on(window.agg_over(v, F.avg, window.over(a, int(p["w"]))))
    if n.op == "MOM":
        return nulls.lift(lambda x, y: x - y, v, window.back(a, int(p["k"])))
    if n.op in AGGREGATES:
        return on(window.agg_over(v, AGGREGATES[n.op](p), window.over(a, int(p["w"]))))
    if n.op == "XAVG":
        return on(window.xavg_column(a, int(p["w"]), p.get("alpha")))
    if n.op == "RSI":
        return on(window.rsi_column(a, int(p.get("w", 14))))
    if n.op == "MACD":
        return on(window.macd_column(a, int(p.get("short", 12)), int(p.get("long", 26))))
    if n.op in COLUMNS:
        return on(COLUMNS[n.op](a, int(p["w"])))
    raise ValueError(f"{n.op} doesn't fuse")


AGGREGATES = {
    "MSTD": lambda p: F.stddev_samp if p.get("ddof", 1) else F.stddev_pop, "MVAR": lambda p: F.var_samp if p.get("ddof", 1) else F.var_pop,
    "MMAX": lambda p: F.max, "MMIN": lambda p: F.min, "MMEDIAN": lambda p: window.median_of(float(p.get("q", 0.5))),
}
COLUMNS = {"WAVG": window.wavg_column, "MSLOPE": window.mslope_column, "ZSCORE": window.zscore_column}
FUSIBLE = {"BASE", "PLUS", "MINUS", "MULT", "DIVIDE", "SCALE", "SEL", "JOIN", "MAVG", "MOM", "XAVG", "RSI", "MACD", *AGGREGATES, *COLUMNS}


def fusible(n: Node) -> bool:
    return all(x.op in FUSIBLE and not (WHOLE | {"kind"}) & {k for k, _ in x.params} for x in walk(n))


def segment_length(n_entries: int, cores: int, model: Model | None = None, least: int = 1024, most: int = 65536) -> int:
    """Entries of a segment by the cost model: the series in as many segments as pay, and at least one for each core."""
    parts = best_partitions(model or published_model(), n_entries, cores)
    return max(least, min(most, -(-n_entries // parts)))


def lower(n: Node, bases: dict[str, SeriesFrame], length: int | None = 1024, interval: tuple[int, int] | None = None, model: Model | None = None) -> SeriesFrame:
    """Evaluate by segments: the interval, widened by the tree's halo, is filtered under the windows; one shuffle by
    (series_id, seg) serves all windows of a fused tree. A tree over several series reads them as columns of one
    frame; one with an operator that has no column form runs operator by operator, its windows still by segments.

    Without a ``length`` the cost model chooses it, from the interval or the calendar."""
    left, right = halo(n)
    names = sorted({str(x.param("name")) for x in walk(n) if x.op == "BASE"})
    some = bases[names[0]]
    if length is None:
        size_ = interval[1] - interval[0] + 1 if interval else some.calendar.n or PUBLISHED_N
        length = segment_length(size_, some.df.sparkSession.sparkContext.defaultParallelism, model)

    def cut(sf: SeriesFrame) -> SeriesFrame:
        return sf.slice(max(0, interval[0] - left), interval[1] + right) if interval else sf

    if fusible(n):
        if len(names) == 1:
            out = core(fuse(n, segment(cut(some), length, left, right)))
        else:
            frame = some.with_df(algebra.wide([cut(bases[k]) for k in names]).withColumn("v", F.col("v0")))
            out = core(fuse(n, segment(frame, length, left, right), {k: f"v{i}" for i, k in enumerate(names)}))
    else:
        out = evaluate(n, {k: cut(bases[k]) for k in names}, length=length)
    return out.slice(*interval) if interval else out


def execute(n: Node, bases: dict[str, SeriesFrame], want: Ranges, cache: Cache | None = None, length: int = 1024, order: str = "top_down", keep: bool | str = False) -> SeriesFrame:
    """Evaluate the wanted segments: stored ones are read, missing ones computed from what their children have.

    With ``keep`` the root's computed segments are stored and published, with "all" those of every sub-tree that is
    computed on the way; what is stored is computed once and read back."""
    return _run(annotate(n, want, cache, length, order), bases, cache, length, keep, {})


def _run(a: Annotated, bases: dict[str, SeriesFrame], cache: Cache | None, length: int, keep: bool | str, done: dict) -> SeriesFrame:
    some = next(iter(bases.values()))
    at = (name(canonical(a.node)), tuple(a.cached), tuple(a.compute))
    if at in done:
        return done[at]
    parts: list[DataFrame] = []
    if a.cached and cache is not None:
        parts.append(cache.read(a.node, a.cached))
    if a.compute and a.node.op == "BASE":
        parts.append(_within(bases[str(a.node.param("name"))], a.compute, length).df.select("series_id", "idx", "v"))
    elif a.compute:
        if cache is not None:
            cache.counts["recomputed"] += size(a.compute)
        kids = [_run(c, bases, cache, length, keep if keep == "all" else False, done) for c in a.children]
        sf = _within(apply_cut(a.node, kids, length), a.compute, length)
        df = sf.df.select("series_id", "idx", "v")
        if keep and cache is not None:
            cache.store_ranges(a.node, df, a.compute)
            df = cache.read(a.node, a.compute)
        parts.append(df)
    df = parts[0]
    for p in parts[1:]:
        df = df.unionByName(p)
    done[at] = some.with_df(df)
    return done[at]


def _within(sf: SeriesFrame, segs: Ranges, length: int) -> SeriesFrame:
    """The entries of these segments; one filter, which reaches the scan."""
    test = F.lit(False)
    for lo, hi in segs:
        test = test | F.col("idx").between(lo * length, (hi + 1) * length - 1)
    return sf.with_df(sf.df.where(test))


def execute_many(trees: list[Node], bases: dict[str, SeriesFrame]) -> list[SeriesFrame]:
    """Several trees with their common sub-trees evaluated, and kept in memory or on disk, once."""
    trees = [canonical(t) for t in trees]
    memo: dict[str, SeriesFrame] = {}
    for s in reversed(shared(trees)):
        sf = evaluate(s, bases, memo)
        memo[name(s)] = sf.with_df(sf.df.persist())
    return [evaluate(t, bases, memo) for t in trees]
