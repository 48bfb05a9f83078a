"""A tabular critic: mean return by position and length bucket, and its losses."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

POSITIONS, LENGTHS = 4, 6


def buckets(trace: DataFrame) -> DataFrame:
    return trace.withColumn("pos_bucket", F.least(F.col("pos"), F.lit(POSITIONS - 1))).withColumn("len_bucket", F.least(F.col("length"), F.lit(LENGTHS)))


def fit(trace: DataFrame) -> DataFrame:
    """pos_bucket, len_bucket, value, n: at most POSITIONS * LENGTHS rows, so that scoring broadcasts a table of fixed size."""
    return buckets(trace).groupBy("pos_bucket", "len_bucket").agg(F.avg("ret").alias("value"), F.count("*").alias("n"))


def score(trace: DataFrame, values: DataFrame) -> DataFrame:
    return buckets(trace).join(F.broadcast(values.select("pos_bucket", "len_bucket", F.col("value").alias("v"))), ["pos_bucket", "len_bucket"], "left").fillna({"v": 0.0})


def value_loss(trace: DataFrame, clip: float | None = None) -> DataFrame:
    """Mean of half the squared error of v against ret; with ``clip``, of the worse of v and v held near v_old."""
    plain = (F.col("v") - F.col("ret")) ** 2
    if clip is None:
        return trace.agg((0.5 * F.avg(plain)).alias("value_loss"))
    held = F.greatest(F.least(F.col("v"), F.col("v_old") + clip), F.col("v_old") - clip)
    return trace.agg((0.5 * F.avg(F.greatest(plain, (held - F.col("ret")) ** 2))).alias("value_loss"))
