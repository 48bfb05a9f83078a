"""Joins that Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from trajkit.ranking import with_range


def as_of(left: DataFrame, right: DataFrame, at: str, since: str, take: list[str], by: list[str] | None = None) -> DataFrame:
    """Each left row with the columns ``take`` of the last right row whose ``since`` is not after the row's ``at``.

    Union, then one window that carries the last right value forward: one shuffle on ``by``. Without ``by`` rows are split
    into ranges of time; the last right row of each range is carried into the ranges after it. Left rows before the first
    right row get nulls. On equal times the right row counts as before.
    """
    by = by or []
    x = left.withColumn("_t", F.col(at)).withColumn("_side", F.lit(1))
    y = right.select(*by, F.col(since).alias("_t"), F.lit(0).alias("_side"), F.struct(*[F.col(c).alias(c) for c in take]).alias("_r"))
    both = x.unionByName(y, allowMissingColumns=True)
    if not by:
        both = with_range(both, F.col("_t"))
        ends = both.groupBy("_part").agg(F.max_by("_r", F.when(F.col("_side") == 0, F.col("_t"))).alias("_end"))
        carry = F.last("_end", ignorenulls=True).over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1))  # one row a range
        both = both.join(F.broadcast(ends.select("_part", carry.alias("_carry"))), "_part")
    w = Window.partitionBy(*(by or ["_part"])).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    found = F.last("_r", ignorenulls=True).over(w)
    both = both.withColumn("_f", found if by else F.coalesce(found, "_carry"))
    return both.filter("_side = 1").select(*left.columns, *[F.col(f"_f.{c}").alias(c) for c in take])


def as_of_few(left: DataFrame, right: DataFrame, at: str, since: str, take: list[str], limit: int = 100_000) -> DataFrame:
    """As ``as_of`` for a right side of at most ``limit`` rows (refits): intervals are broadcast, the left side isn't shuffled.

    Intervals are cut at the bounds of as many equal buckets of time as there are intervals, so an equi-join finds them.
    """
    n, low, high = right.agg(F.count("*"), F.min(since), F.max(since)).first()
    if n > limit:
        return as_of(left, right, at, since, take)
    width = max(1, ((high or 0) - (low or 0)) // max(1, n))
    bucket = lambda c: F.floor((F.least(c, F.lit(high)) - F.lit(low)) / width)  # noqa: E731  times after the last start share its bucket
    spans = right.select(F.col(since).alias("_from"), F.lead(since).over(Window.orderBy(since)).alias("_to"), *take)  # at most ``limit`` rows
    spans = spans.withColumn("_b", F.explode(F.sequence(bucket(F.col("_from")), bucket(F.coalesce("_to", F.lit(high))))))
    x = left.withColumn("_b", bucket(F.col(at)))
    on = (F.col("_x._b") == F.col("_s._b")) & (F.col(at) >= F.col("_from")) & (F.col("_to").isNull() | (F.col(at) < F.col("_to")))
    return x.alias("_x").join(F.broadcast(spans.alias("_s")), on, "left").select(*[F.col(f"_x.{c}") for c in left.columns], *[F.col(f"_s.{c}") for c in take])


def range_join(left: DataFrame, right: DataFrame, at: Column, low: Column, high: Column, width: float) -> DataFrame:
    """Rows with low <= at < high, as an equi-join on buckets of ``width`` with the exact condition after it."""
    x = left.withColumn("_b", F.floor(at / width))
    y = right.withColumn("_b", F.explode(F.sequence(F.floor(low / width), F.floor(high / width))))
    return x.join(y, "_b").filter((at >= low) & (at < high)).drop("_b")
