"""Prompt groups: assembly, completeness, statistics, dynamic filtering and backfill, rewards counted once."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from trajkit.ranking import global_rank


def assemble(rollouts: DataFrame, n: int) -> DataFrame:
    """One row per group: rollouts, graded rollouts, whether n of them are graded, and the completion time of the last."""
    return rollouts.groupBy("group_id").agg(F.count("*").alias("n_rollouts"), F.count("reward").alias("n_graded"), F.max("completed_at").alias("completed_at")).withColumn("complete", F.col("n_graded") >= n)


def complete(rollouts: DataFrame, n: int) -> DataFrame:
    """Rollouts of complete groups; partial groups are held back."""
    return rollouts.join(assemble(rollouts, n).filter("complete").select("group_id"), "group_id", "left_semi")


def take_samples(rollouts: DataFrame, n: int) -> DataFrame:
    """The first n rollouts of each group by completion, ties by id, of groups that have n."""
    w = Window.partitionBy("group_id")
    order = w.orderBy("completed_at", "rollout_id")
    return rollouts.withColumn("sample", F.row_number().over(order)).withColumn("_n", F.count("*").over(w)).filter((F.col("sample") <= n) & (F.col("_n") >= n)).drop("_n")


def stats(rollouts: DataFrame, ddof: int = 1, reward: str = "reward") -> DataFrame:
    sd = F.stddev_samp(reward) if ddof else F.stddev_pop(reward)
    return rollouts.groupBy("group_id").agg(F.count(reward).alias("n"), F.avg(reward).alias("mean"), sd.alias("std"), F.min(reward).alias("low"), F.max(reward).alias("high"))


def drop_degenerate(rollouts: DataFrame, eps: float = 0.0, reward: str = "reward") -> DataFrame:
    """Rollouts of groups whose rewards differ; max - min is exact where a standard deviation isn't."""
    g = rollouts.groupBy("group_id").agg((F.max(reward) - F.min(reward)).alias("_spread")).filter(F.col("_spread") > eps)
    return rollouts.join(g.select("group_id"), "group_id", "left_semi")


def backfill(rollouts: DataFrame, batch_groups: int, fill: bool = True) -> DataFrame:
    """Groups that survive the dynamic filter, ranked by completion and cut into batches.

    With ``fill`` every batch has ``batch_groups`` groups, later complete groups taking the places of degenerate ones; without,
    batches are cut before the filter and come out short.
    """
    g = rollouts.groupBy("group_id").agg(F.max("completed_at").alias("completed_at"), (F.max("reward") - F.min("reward")).alias("_spread"))
    alive = F.col("_spread") > 0
    ranked = global_rank(g.filter(alive) if fill else g, F.unix_micros(F.col("completed_at").cast("timestamp")), ["group_id"])
    out = ranked if fill else ranked.filter(alive)
    return out.select("group_id", "rank", F.floor((F.col("rank") - 1) / batch_groups).alias("batch"))


def filter_whole(rollouts: DataFrame, keep: Column, how: str = "all") -> DataFrame:
    """A predicate on rollouts lifted to groups: a group stays whole or goes whole."""
    test = {"all": F.bool_and, "any": F.bool_or}[how](keep)
    return rollouts.join(rollouts.groupBy("group_id").agg(test.alias("_keep")).filter("_keep").select("group_id"), "group_id", "left_semi")


def overlong(lengths: DataFrame, cap: int, buffer: int) -> DataFrame:
    """Truncated responses are masked; lengths inside the buffer before the cap are penalised in proportion."""
    soft = -(F.col("length") - (cap - buffer)) / buffer
    return lengths.withColumn("masked", F.col("length") > cap).withColumn("penalty", F.when(F.col("length") <= cap - buffer, 0.0).when(F.col("length") > cap, -1.0).otherwise(soft))


def fan_out(results: DataFrame, segments: DataFrame) -> DataFrame:
    """Rollout-level results mapped back to segments; rewards were counted before, once per rollout."""
    return segments.join(results, "rollout_id")


def segment_counted_stats(rollouts: DataFrame, segments: DataFrame) -> DataFrame:
    """The naive mean that counts a reward once per segment, beside the mean that counts it once per rollout."""
    per = segments.groupBy("rollout_id").agg(F.countDistinct("segment_seq").alias("k"))
    r = rollouts.join(per, "rollout_id")
    return r.groupBy("group_id").agg((F.sum(F.col("reward") * F.col("k")) / F.sum("k")).alias("by_segment"), F.avg("reward").alias("by_rollout"))
