"""Two nulls beside the reals: empty (SQL NULL, or no row in a sparse frame) and unknown (NaN).

The states are ordered real < empty < unknown; a pointwise operation has the largest state among its inputs."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

UNKNOWN = float("nan")


def unknown() -> Column:
    return F.lit(UNKNOWN)


def empty() -> Column:
    return F.lit(None).cast("double")


def is_unknown(c: Column) -> Column:
    return F.coalesce(F.isnan(c), F.lit(False))


def state(c: Column) -> Column:
    return F.when(is_unknown(c), "unknown").when(c.isNull(), "empty").otherwise("value")


def any_of(flags: list[Column]) -> Column:
    out = flags[0]
    for f in flags[1:]:
        out = out | f
    return out


def lift(fn: Callable[..., Column], *cols: Column) -> Column:
    """``fn`` where all inputs are real, else the largest state among them."""
    return F.when(any_of([is_unknown(c) for c in cols]), unknown()).when(any_of([c.isNull() for c in cols]), empty()).otherwise(fn(*cols))


def combine(*cols: Column) -> Column:
    """The state that a pointwise operation on these has."""
    return F.when(any_of([is_unknown(c) for c in cols]), "unknown").when(any_of([c.isNull() for c in cols]), "empty").otherwise("value")


def divide(a: Column, b: Column) -> Column:
    """a / b, unknown where b is 0."""
    return F.when(b == 0, unknown()).otherwise(a / F.when(b != 0, b))


def known(pred: Column, c: Column) -> Column:
    """A predicate that an unknown value never fulfils, as NaN is above every number in Spark."""
    return F.coalesce(pred, F.lit(False)) & ~is_unknown(c)
