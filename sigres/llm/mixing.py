"""Mixing sources to target weights by a time-varying curriculum.

Each source has a weight schedule over training time 0..1, piecewise linear.  Its integral is the
source's share of all tokens; inverting the cumulative demand gives, for the c-th token of a
source, the time at which training asks for it.  Documents stand in a fixed pseudo-random order in
their source, are passed over once or more until the source's target is met, and are sorted by
their time over all sources.

Skew: running sums inside a source go over hash buckets whose number follows the source's own row
count, so a source with a third of all rows is many small windows; the sums of buckets are then
summed per source.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sigres.plans.scratch import Scratch, small_side

#: Weights of the sources in code point order, repeating.
WEIGHTS = (5.0, 2.0, 1.0)
#: Tokens that the mix has, as a share of all tokens, and the most that one source may be repeated.
TOTAL_SHARE, MAX_EPOCHS = 1.5, 2.0
#: Rows of a bucket of one source's order, at least; grows with the square root of the source.
BUCKET_ROWS = 512
#: Sources up to which their table is broadcast (about 10 MB).
BROADCAST_SOURCES = 100_000
#: Relative weight of a source over training time: (time, level) knots by position, repeating.
SCHEDULES = (((0.0, 1.5), (1.0, 0.5)), ((0.0, 1.0), (1.0, 1.0)), ((0.0, 0.5), (0.5, 1.0), (1.0, 1.5)))


def word_count(text: Column) -> Column:
    """Runs of characters other than U+0020 and U+0009 to U+000D; null has none."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def water_fill(sources: DataFrame, total_share: float = TOTAL_SHARE, max_epochs: float = MAX_EPOCHS) -> DataFrame:
    """Add ``target`` to (source, n, source_size, weight): shares by weight of ``total_share`` of all
    sizes, none above ``max_epochs`` times its own size, the excess shared again by weight.

    In order of cap over weight, the sources that hit their cap come first: source i does if the
    level that is left for it and all after it is at least its own cap over weight.  One row per
    source, so one task.
    """
    order = Window.orderBy("ratio", "source")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    everyone = order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    level = ((F.lit(total_share) * F.sum("source_size").over(everyone) - F.coalesce(F.sum("cap").over(before), F.lit(0.0)))
             / (F.sum("weight").over(everyone) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))))
    filled = (sources.withColumn("cap", F.lit(max_epochs) * F.col("source_size"))
              .withColumn("ratio", F.col("cap") / F.col("weight"))
              .withColumn("level", level).withColumn("full", F.col("level") >= F.col("ratio")))
    last = F.coalesce(F.min(F.when(~F.col("full"), F.struct("ratio", "level"))).over(everyone)["level"], F.lit(0.0))
    return (filled.withColumn("target", F.when(F.col("full"), F.col("cap")).otherwise(last * F.col("weight")))
            .drop("cap", "ratio", "level", "full"))


def source_table(sized: DataFrame, weights: Sequence[float] = WEIGHTS, **share) -> DataFrame:
    """(source, size) rows -> one row per source: source, n, source_size, weight, at, target."""
    per = sized.groupBy("source").agg(F.count("*").alias("n"), F.sum("size").alias("source_size"))
    at = (F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1)
    weight = F.get(F.array(*[F.lit(float(w)) for w in weights]), F.col("at") % len(weights))
    return water_fill(per.withColumn("at", at).withColumn("weight", weight), **share)


def running_sums(sized: DataFrame, sources: DataFrame, scratch: Scratch) -> DataFrame:
    """Add ``before``, the sizes of the source's documents that stand earlier in its order.

    The order is that of the MD5 of doc_id, then doc_id; it does not depend on partitions.
    """
    per = F.greatest(F.lit(BUCKET_ROWS), F.ceil(F.sqrt("n")))
    # 28 bits of the digest cut the order into as many equal ranges as the source needs
    place = F.conv(F.substring("rank", 1, 7), 16, 10).cast("long")
    keyed = (sized.join(sources.select("source", "target", "source_size", "at", F.ceil(F.col("n") / per).alias("buckets")),
                        sized["source"].eqNullSafe(sources["source"])).drop(sources["source"])
             .withColumn("rank", F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))
             .withColumn("bucket", F.floor(place * F.col("buckets") / F.lit(float(1 << 28)))))
    keyed = scratch.save(keyed, "keyed")
    totals = keyed.groupBy("at", "bucket").agg(F.sum("size").alias("bucket_size"))
    upto = Window.partitionBy("at").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    totals = scratch.save(totals.select("at", "bucket", F.coalesce(F.sum("bucket_size").over(upto), F.lit(0)).alias("offset")), "totals")
    inside = (Window.partitionBy("at", "bucket").orderBy("rank", "doc_id", "size")
              .rowsBetween(Window.unboundedPreceding, -1))
    return (keyed.withColumn("inner", F.coalesce(F.sum("size").over(inside), F.lit(0)))
            .join(small_side(totals, BROADCAST_SOURCES), ["at", "bucket"])
            .withColumn("before", F.col("offset") + F.col("inner")).drop("inner", "offset", "bucket"))


def taken_words() -> Column:
    """Words that the mix takes of a document, over all passes; the pass that meets the target may
    take only the first words of the document in which it does."""
    goal = F.round("target").cast("long")
    # whole passes, then what the last pass still takes of this document
    whole = F.when(F.col("source_size") > 0, F.floor(goal / F.greatest(F.col("source_size"), F.lit(1)))).otherwise(F.lit(0))
    left = goal - whole * F.col("source_size")
    return (whole * F.col("size") + F.greatest(F.lit(0), F.least(F.col("size"), left - F.col("before")))).cast("long")


def mix(docs: DataFrame, weights: Sequence[float] = WEIGHTS, total_share: float = TOTAL_SHARE,
        max_epochs: float = MAX_EPOCHS) -> DataFrame:
    """One row per row of ``docs``: doc_id, source, size, source_size, target, before, taken, at.

    Null text has size 0; null source is a source of its own, the last one.  A document without
    words takes 0.  Repeated rows are documents of their own.  An empty table gives an empty result.
    """
    scratch = Scratch(docs.sparkSession, "mix")
    sized = scratch.save(docs.select("doc_id", "source", word_count(F.col("text")).alias("size")), "sized")
    sources = scratch.save(source_table(sized, weights, total_share=total_share, max_epochs=max_epochs), "sources")
    placed = running_sums(sized, small_side(sources, BROADCAST_SOURCES), scratch)
    return placed.withColumn("taken", taken_words()).drop("rank", "buckets")


def demand_inverse(share: Column, knots: Sequence[tuple[float, float]]) -> Column:
    """Time at which the integral of a piecewise-linear schedule reaches ``share`` of its whole."""
    areas = [(b[0] - a[0]) * (a[1] + b[1]) / 2 for a, b in zip(knots, knots[1:])]
    want = share * sum(areas)
    out, done = None, sum(areas)
    for (t0, w0), (t1, w1), area in reversed(list(zip(knots, knots[1:], areas))):
        done -= area
        slope = (w1 - w0) / (t1 - t0)
        rest = F.greatest(F.lit(0.0), want - F.lit(done))
        # solve w0 x + slope x^2 / 2 = rest in the form that is stable for small slopes
        root = F.sqrt(F.greatest(F.lit(0.0), F.lit(w0 * w0) + 2 * slope * rest))
        time = F.lit(t0) + 2 * rest / F.greatest(F.lit(1e-12), F.lit(w0) + root)
        out = time if out is None else F.when(want < done + area, time).otherwise(out)
    return F.least(F.lit(knots[-1][0]), out)


def passes(mixed: DataFrame, schedules=SCHEDULES) -> DataFrame:
    """Rows of ``mix`` -> one row per document and pass: epoch, words and position are added."""
    last = F.ceil(F.col("taken") / F.greatest(F.col("size"), F.lit(1))).cast("int")
    rows = (mixed.where("taken > 0").withColumn("epoch", F.explode(F.sequence(F.lit(0), last - 1)))
            .withColumn("words", F.least(F.col("size"), F.col("taken") - F.col("epoch") * F.col("size"))))
    share = F.least(F.lit(1.0), (F.col("epoch") * F.col("source_size") + F.col("before") + F.col("words") / 2) / F.col("target"))
    time = None
    for k, knots in enumerate(schedules):
        here = demand_inverse(share, knots)
        time = here if time is None else F.when(F.col("at") % len(schedules) == k, here).otherwise(time)
    return rows.withColumn("position", time)


def training_order(docs: DataFrame, schedules=SCHEDULES, **options) -> DataFrame:
    """The rows of ``mix`` in training order: ``taken`` summed over the passes, ``epochs``, their number, and ``position``, that of the first.

    Range-partitioned and sorted by position; documents that are not taken have none and stand last.
    """
    mixed = Scratch(docs.sparkSession, "order").save(mix(docs, **options), "mixed")
    # a row is known by what stands before it, as only rows without words share that and they are not taken
    row = ["doc_id", "source", "size", "source_size", "target", "before", "at"]
    taken = passes(mixed, schedules).groupBy(*row).agg(
        F.sum("words").alias("taken"), F.count("*").alias("epochs"), F.min("position").alias("position"))
    idle = mixed.where("taken = 0").select(*row, "taken", F.lit(0).cast("long").alias("epochs"), F.lit(None).cast("double").alias("position"))
    order = [F.col("position").asc_nulls_last(), F.col("doc_id")]
    return taken.unionByName(idle).repartitionByRange(*order).sortWithinPartitions(*order)


def curriculum(docs: DataFrame, schedules=SCHEDULES, **options) -> DataFrame:
    """The training order: one row per document and pass, sorted by time.

    Columns: doc_id, source, epoch, words (taken in this pass, the first ones of the text), position
    (time 0..1 at which the middle of the document is due).  Range-partitioned and sorted by
    position, so consecutive partitions are consecutive training steps.
    """
    return (passes(mix(docs, **options), schedules).select("doc_id", "source", "epoch", "words", "position")
            .repartitionByRange("position", "doc_id", "epoch").sortWithinPartitions("position", "doc_id", "epoch"))


ORACLE = r"""
WITH RECURSIVE d AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size FROM documents
), s AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size,
         (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 AS k, [5.0, 2.0, 1.0][1 + k]::DOUBLE AS w
  FROM d GROUP BY source
), fill AS (
  SELECT 0 AS round, source, source_size, k, w, false AS capped, CAST(NULL AS DOUBLE) AS target FROM s
  UNION ALL
  SELECT round + 1, source, source_size, k, w, capped OR lev * w >= 2.0 * source_size,
         CASE WHEN capped OR lev * w >= 2.0 * source_size THEN 2.0 * source_size ELSE lev * w END
  FROM (SELECT *, (1.5 * sum(source_size) OVER () - coalesce(sum(CASE WHEN capped THEN 2.0 * source_size END) OVER (), 0))
                  / nullif(sum(CASE WHEN capped THEN 0 ELSE w END) OVER (), 0) AS lev FROM fill)
  WHERE round < 64
), t AS (
  SELECT source, source_size, k, target, CAST(round(target) AS BIGINT) AS goal FROM fill WHERE round = 64
), o AS (
  SELECT doc_id, size, source_size, k, target, goal,
         coalesce(sum(size) OVER (PARTITION BY d.source ORDER BY md5(CAST(doc_id AS VARCHAR)), doc_id
                                  ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source
), m AS (
  SELECT *, CAST(CASE WHEN source_size = 0 THEN 0 ELSE (goal // source_size) * size
            + greatest(0, least(size, goal - (goal // source_size) * source_size - before)) END AS BIGINT) AS taken FROM o
), p AS (
  -- demand of the middle of the first pass as a share of the source's, and the time at which its schedule's integral is that share
  SELECT *, least(1.0, (before + least(size, taken) / 2) / target) AS q FROM m
)
SELECT doc_id, size, source_size, round(target, 6) AS target, taken, CASE WHEN taken = 0 THEN 0 ELSE (taken + size - 1) // size END AS epochs,
       round(CASE WHEN taken > 0 THEN CASE k WHEN 0 THEN 1.5 - sqrt(2.25 - 2 * q) WHEN 1 THEN q ELSE sqrt(0.25 + 2 * q) - 0.5 END END, 6) AS position
FROM p
"""
