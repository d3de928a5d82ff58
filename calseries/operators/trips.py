"""Driving indicators: scalar functions of a trip's series, all from one pass over one ordering.

Input rows: trip_id, t (seconds from the trip's start), v (km/h), and where at hand gear, rpm, limit."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .. import nulls

STOP_SPEED = 2.0
BRAKE = -0.02


def steps(trips: DataFrame, stop: float = STOP_SPEED, brake: float = BRAKE, tie: str = "t") -> DataFrame:
    """Each measure with its step from the one before: dt, dv, a, and where stops, brakes, shifts and extrema begin."""
    w = Window.partitionBy("trip_id").orderBy("t", tie) if tie != "t" else Window.partitionBy("trip_id").orderBy("t")
    has = lambda c: c in trips.columns
    d = trips.withColumn("v0", F.lag("v").over(w)).withColumn("dt", (F.col("t") - F.lag("t").over(w)).cast("double"))
    d = d.withColumn("dv", F.col("v") - F.col("v0")).withColumn("a", F.when(F.col("dt") > 0, F.col("dv") / F.col("dt")))
    d = d.withColumn("still", F.col("v") < stop).withColumn("braking", F.coalesce(F.col("a") < brake, F.lit(False))).withColumn("slower", F.coalesce(F.col("a") < 0, F.lit(False)))
    d = d.withColumn("stop_on", F.col("still") & ~F.coalesce(F.lag("still").over(w), F.lit(False)))
    d = d.withColumn("brake_on", F.col("braking") & ~F.coalesce(F.lag("braking").over(w), F.lit(False)))
    d = d.withColumn("turn", F.coalesce(F.signum("dv") * F.signum(F.lag("dv").over(w)) < 0, F.lit(False)))
    d = d.withColumn("shift", F.coalesce(F.col("gear") != F.lag("gear").over(w), F.lit(False)) if has("gear") else F.lit(False))
    # a decelerating run ends where the next step isn't slower; it counts if it ends in a stop
    ends = F.col("slower") & ~F.coalesce(F.lead("slower").over(w), F.lit(False))
    d = d.withColumn("run", F.sum(F.when(F.col("slower") & ~F.coalesce(F.lag("slower").over(w), F.lit(False)), 1).otherwise(0)).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    d = d.withColumn("run_stops", ends & F.col("still"))
    return d


def safe(x: Column, y: Column) -> Column:
    return F.when(y != 0, x / y)


RULES = ("right", "trapezoid")


def indicators(trips: DataFrame, rule: str = "right", stop: float = STOP_SPEED, brake: float = BRAKE, tie: str = "t") -> DataFrame:
    """One row per trip with every indicator; a division by zero gives NULL here, as there is one entry only.

    ``rule`` says how integrals over a step are taken: from its right end, or as the mean of both ends. A measure
    without an acceleration of its own, as the first, has that of the step after it."""
    if rule not in RULES:
        raise ValueError(f"unknown rule: {rule}")
    d = steps(trips, stop, brake, tie)
    rising = F.greatest(F.col("a"), F.lit(0.0))
    d = d.withColumn("power", F.when(F.col("a").isNotNull(), F.col("v") * rising))
    if rule == "trapezoid":
        w = Window.partitionBy("trip_id").orderBy("t", tie) if tie != "t" else Window.partitionBy("trip_id").orderBy("t")
        d = d.withColumn("power", (F.col("power") + F.coalesce(F.lag("power").over(w), F.col("v0") * rising)) / 2)
    speed = F.col("v") if rule == "right" else (F.col("v") + F.col("v0")) / 2
    run = Window.partitionBy("trip_id", "run")
    d = d.withColumn("km", speed * F.col("dt") / 3600.0)
    d = d.withColumn("run_hits", F.max(F.col("run_stops").cast("int")).over(run))
    dist, dur = F.sum("km"), F.sum("dt")
    work = F.sum(F.when(F.col("dt") > 0, F.col("power") * F.col("dt")))
    rise = F.when(F.col("dv") > 0, F.col("v") * F.col("v") - F.col("v0") * F.col("v0")).otherwise(0.0)
    braked = F.when(F.col("slower") & (F.col("run_hits") == 1), F.col("v0") * F.col("dt") / 3600.0)
    has = lambda c: c in trips.columns
    cols = [
        F.count(F.lit(1)).alias("n"), dur.alias("duration"), dist.alias("distance"), F.avg("v").alias("avg_speed"), F.avg(F.when(~F.col("still"), F.col("v"))).alias("avg_driving_speed"),
        F.avg("a").alias("avg_accel"), F.avg(F.when(F.col("a") > 0, F.col("a"))).alias("avg_positive_accel"),
        safe(work, dur).alias("rpa"), safe(work, dist).alias("rpa_distance"),
        safe(F.sum(rise), dur).alias("pke"), safe(F.sum(rise), dist).alias("pke_distance"),
        safe(F.sum(F.when(F.col("still"), F.col("dt")).otherwise(0.0)), dur).alias("pst"),
        F.count_if("stop_on").alias("stops"), safe(F.sum(F.when(F.col("still"), F.col("dt"))), F.count_if("stop_on").cast("double")).alias("mean_stop"),
        F.count_if("brake_on").alias("brakes"), safe(F.count_if("brake_on").cast("double"), dist).alias("brakes_per_km"),
        F.count_if("shift").alias("gear_shifts"), safe(F.count_if("shift").cast("double"), dist).alias("shifts_per_km"),
        F.count_if("turn").alias("extrema"), safe(F.sum(braked), F.count_if("run_stops").cast("double")).alias("braking_distance"),
    ]
    if has("rpm"):
        cols.append(F.avg("rpm").alias("avg_rpm"))
    if has("limit"):
        cols.append(safe(F.sum(F.when(F.col("v") > F.col("limit"), F.col("dt")).otherwise(0.0)), dur).alias("overspeed"))
    return d.groupBy("trip_id").agg(*cols)


def pke_steps(v: Column, prev: Column, momentum: Column) -> Column:
    """Rise of the squared speed where the momentum is positive."""
    return F.when(nulls.known(momentum > 0, momentum), v * v - prev * prev)


def pke_literal(v: Column, prev: Column, momentum: Column) -> Column:
    """The same with each speed multiplied by the selected momentum before squaring, as an algebra tree would."""
    return F.when(nulls.known(momentum > 0, momentum), F.pow(v * momentum, F.lit(2.0)) - F.pow(prev * momentum, F.lit(2.0)))


def compare_styles(per_trip: DataFrame, styles: DataFrame, columns: list[str], normal: str = "normal") -> DataFrame:
    """Mean indicators by driver and style, and their difference to that driver's normal style. ``styles`` has one row
    per trip: trip_id, driver, style."""
    rows = per_trip.join(styles, "trip_id").groupBy("driver", "style").agg(*[F.avg(c).alias(c) for c in columns])
    w = Window.partitionBy("driver")
    return rows.select("driver", "style", *columns, *[(F.col(c) - F.max(F.when(F.col("style") == normal, F.col(c))).over(w)).alias(f"{c}_diff") for c in columns])


def correlation(per_trip: DataFrame, columns: list[str]) -> DataFrame:
    """Pearson correlation of every pair of indicators, as rows."""
    pairs = [(a, b) for i, a in enumerate(columns) for b in columns[i + 1 :]]
    one = per_trip.agg(*[F.corr(a, b).alias(f"p{i}") for i, (a, b) in enumerate(pairs)])
    return one.select(F.inline(F.array(*[F.struct(F.lit(a).alias("x"), F.lit(b).alias("y"), F.col(f"p{i}").alias("r")) for i, (a, b) in enumerate(pairs)])))


def principal_components(per_trip: DataFrame, columns: list[str], k: int = 2) -> DataFrame:
    """The first ``k`` principal components of the standardised indicators (trip_id, pc)."""
    from pyspark.ml.feature import PCA, StandardScaler, VectorAssembler
    from pyspark.ml.functions import vector_to_array

    rows = VectorAssembler(inputCols=columns, outputCol="_x", handleInvalid="skip").transform(per_trip)
    scaled = StandardScaler(inputCol="_x", outputCol="_z", withMean=True).fit(rows).transform(rows)
    return PCA(k=k, inputCol="_z", outputCol="_pc").fit(scaled).transform(scaled).select("trip_id", vector_to_array("_pc").alias("pc"))
