"""Mixing sources to target weights, with DataFrame functions only.

Each document gets a hash-random key. Keys are evenly spread, so equal ranges of them cut every source, a hot one too,
into parts of like size; a running sum inside each part and the sums of the parts before give each document the words
of its source that come before it. A source is taken whole as often as its target allows, then up to the rest of its
budget: to the very word (``cut="word"``), or to the document whose middle is the last before it (``cut="document"``,
which leaves every text whole).

Defined cases: a null or empty text has no words and is never taken; a null source is a source of its own, last in
order; repeated rows are taken by turns, each at most ``max_epochs`` times; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import WORD, fresh, staged, table

WEIGHTS = (5, 2, 1)
SHARE = 1.5
MAX_EPOCHS = 2
#: Hexadecimal digits of the key that name a part: 16 ** 3 parts a source.
PART_DIGITS = 3


def word_count(text: str = "text") -> Column:
    return F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long")


def random_key(seed: str) -> Column:
    return F.md5(F.concat(F.lit(seed), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))


def targets(sizes: DataFrame, weights=WEIGHTS, share: float = SHARE, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """(source, source_size) with one row a source -> the same with its target.

    Shares by weight that exceed the cap of a source go to the others by weight until none does. In order of cap per
    weight the capped sources come first, so running sums give each source the level that holds if it is the first
    one not capped; the first whose cap isn't reached sets the level for all after it."""
    order = Window.orderBy(F.col("source").isNull(), "source")
    w = F.element_at(F.array(*[F.lit(x) for x in weights]), (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int"))
    s = sizes.withColumn("w", w.cast("double")).withColumn("cap", F.col("source_size") * F.lit(float(max_epochs)))
    by_cap = Window.orderBy(F.col("cap") / F.col("w"), F.col("source").isNull(), "source")
    every = Window.partitionBy()
    s = (
        s.withColumn("budget", F.sum("source_size").over(every) * F.lit(share))
        .withColumn("room", F.col("budget") - (F.sum("cap").over(by_cap) - F.col("cap")))
        .withColumn("weight_left", F.sum("w").over(every) - (F.sum("w").over(by_cap) - F.col("w")))
        .withColumn("open", F.col("w") * F.col("room") / F.col("weight_left") <= F.col("cap"))
    )
    level = F.first(F.when(F.col("open"), F.struct("room", "weight_left")), ignorenulls=True).over(by_cap)
    s = s.withColumn("level", level)
    goal = F.when(F.col("level").isNull(), F.col("cap")).otherwise(F.col("w") * F.col("level.room") / F.col("level.weight_left"))
    return s.select("source", "source_size", F.when(F.col("source_size") == 0, F.lit(0.0)).otherwise(goal).alias("target"))


def draw(docs: DataFrame, seed: str = "mix", cut: str = "word", weights=WEIGHTS, share: float = SHARE, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """source, key, doc_id, size, source_size, target, epochs, taken for every row of ``docs`` (doc_id, source, text)."""
    if cut not in ("word", "document"):
        raise ValueError(f"unknown cut: {cut}")
    key = random_key(seed)
    sized = staged(docs.select("doc_id", "source", word_count().alias("size"), key.alias("key")), "sizes").withColumn("part", F.substring("key", 1, PART_DIGITS))
    parts = sized.groupBy("source", "part").agg(F.sum("size").alias("part_size"))
    goal = targets(parts.groupBy("source").agg(F.sum("part_size").alias("source_size")), weights, share, max_epochs)
    before = F.sum("part_size").over(Window.partitionBy("source").orderBy("part")) - F.col("part_size")
    cuts = (
        parts.withColumn("before", before).withColumnRenamed("source", "s").withColumnRenamed("part", "p")
        .join(goal, F.col("s").eqNullSafe(F.col("source"))).drop("source", "part_size")
    )
    here = Window.partitionBy("source", "part").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, 0)
    running = sized.withColumn("within", F.sum("size").over(here) - F.col("size"))
    rows = running.join(cuts, F.col("source").eqNullSafe(F.col("s")) & (F.col("part") == F.col("p")))
    epochs = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0)
    rest = F.col("target") - F.col("epochs") * F.col("source_size")
    start = F.col("before") + F.col("within")
    if cut == "word":
        extra = F.least(F.col("size"), F.greatest(F.lit(0), F.floor("rest") - start))
    else:
        extra = F.when(start + F.col("size") / 2.0 <= F.col("rest"), F.col("size")).otherwise(0)
    taken = F.least(F.col("epochs") * F.col("size") + extra, F.lit(max_epochs) * F.col("size"))
    return (
        rows.withColumn("epochs", epochs.cast("long")).withColumn("rest", rest)
        .select("source", "key", "doc_id", "size", "source_size", "target", "epochs", taken.cast("long").alias("taken"))
    )


def mix(docs: DataFrame, seed: str = "mix", **how) -> DataFrame:
    """The rows of ``docs`` as often as the mix takes them, whole, with all their columns.

    Only the last row that each source takes once more is looked up; every row then decides for itself. Rows that share
    the last one's place (they repeat its id and size) are told apart by their number, in the order of their texts."""
    drawn = draw(docs, seed, cut="document", **how)
    more = F.col("taken") > F.col("epochs") * F.col("size")
    place = F.struct("key", "doc_id", "size")
    source, epochs, last, ties, at, mine, tie, times, copy = fresh(docs, "mix_source", "mix_epochs", "mix_last", "mix_ties", "mix_key", "mix_place", "mix_tie", "mix_times", "mix_copy")
    ends = drawn.groupBy("source").agg(F.max("epochs").alias(epochs), F.max(F.when(more, place)).alias(last))
    same = drawn.where(more).join(F.broadcast(ends.select(F.col("source").alias("s"), last)), F.col("source").eqNullSafe(F.col("s")) & (place == F.col(last)))
    passed = same.groupBy(F.col("source").alias("s")).agg(F.count(F.lit(1)).alias(ties))
    ends = ends.join(passed, F.col("source").eqNullSafe(F.col("s")), "left").select(F.col("source").alias(source), epochs, last, ties)

    rows = docs.withColumn(at, random_key(seed)).withColumn(mine, F.struct(F.col(at).alias("key"), F.col("doc_id"), word_count().alias("size")))
    rows = rows.join(F.broadcast(ends), F.col("source").eqNullSafe(F.col(source)))  # one row a source
    tied = F.col(mine) == F.col(last)
    order = Window.partitionBy(source).orderBy(F.xxhash64(F.col("text").cast("string")))
    before = rows.where(~F.coalesce(tied, F.lit(False))).withColumn(tie, F.lit(0))
    level = rows.where(tied).withColumn(tie, F.row_number().over(order))
    rows = before.unionByName(level)
    once_more = F.coalesce(((F.col(mine) < F.col(last)) | (tied & (F.col(tie) <= F.col(ties)))).cast("long"), F.lit(0))
    rows = rows.withColumn(times, F.when(F.col(mine)["size"] > 0, F.col(epochs) + once_more).otherwise(0)).where(F.col(times) > 0)
    return rows.select(*docs.columns, F.explode(F.sequence(F.lit(1), F.col(times).cast("int"))).alias(copy)).drop(copy)


def op4_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return draw(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


OP4_SQL = r"""
WITH sized AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size,
         md5('mix' || coalesce(CAST(doc_id AS VARCHAR), '')) AS key
  FROM documents),
s0 AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source),
s1 AS (SELECT *, CAST([5, 2, 1][1 + (row_number() OVER (ORDER BY source IS NULL, source) - 1) % 3] AS DOUBLE) AS w,
         source_size * 2.0 AS cap FROM s0),
s2 AS (SELECT *, CAST(sum(source_size) OVER () AS DOUBLE) * 1.5 - (sum(CAST(cap AS DOUBLE)) OVER o - CAST(cap AS DOUBLE)) AS room,
         sum(w) OVER () - (sum(w) OVER o - w) AS weight_left
       FROM s1 WINDOW o AS (ORDER BY CAST(cap AS DOUBLE) / w, source IS NULL, source ROWS UNBOUNDED PRECEDING)),
s3 AS (SELECT *, row_number() OVER (ORDER BY CAST(cap AS DOUBLE) / w, source IS NULL, source) AS k,
         w * room / weight_left <= cap AS open FROM s2),
lev AS (SELECT min_by(room, k) AS room, min_by(weight_left, k) AS weight_left, min(k) AS k FROM s3 WHERE open),
goal AS (SELECT s3.source, s3.source_size,
           CASE WHEN s3.source_size = 0 THEN 0.0
                WHEN lev.k IS NULL OR s3.k < lev.k THEN CAST(s3.cap AS DOUBLE)
                ELSE s3.w * lev.room / lev.weight_left END AS target FROM s3 CROSS JOIN lev),
run AS (SELECT *, sum(size) OVER (PARTITION BY source ORDER BY key, doc_id, size ROWS UNBOUNDED PRECEDING) - size AS before FROM sized),
j AS (SELECT r.doc_id, r.size, r.before, g.source_size, CAST(g.target AS DOUBLE) AS target,
        CASE WHEN g.source_size > 0 THEN CAST(floor(g.target / g.source_size) AS BIGINT) ELSE 0 END AS epochs
      FROM run r JOIN goal g ON r.source IS NOT DISTINCT FROM g.source)
SELECT doc_id, size, source_size, target,
  CAST(least(epochs * size + least(size, greatest(0, CAST(floor(target - epochs * source_size) AS BIGINT) - before)), 2 * size) AS BIGINT) AS taken
FROM j
"""
