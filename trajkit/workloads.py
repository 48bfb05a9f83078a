"""Fixtures on the given tables: rollouts, action tokens, requests, lifecycles, experiences."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

SAMPLES, GROUPS_PER_STEP, MISMATCH = 4, 32, 20.0


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def rollouts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One order is one rollout of its customer's prompt: binary and continuous reward, completion time."""
    o = table(spark, sf_dir, "orders")
    return o.select(
        F.col("o_custkey").alias("group_id"), F.col("o_orderkey").alias("rollout_id"), F.col("o_orderdate").alias("completed_at"),
        (F.col("o_orderstatus") == "F").cast("double").alias("reward"), (F.col("o_totalprice") / 1e5).alias("reward_c"), F.col("o_orderpriority").alias("gate_hint"),
    )


def action_tokens(spark: SparkSession, sf_dir: str, mismatch: float = MISMATCH) -> DataFrame:
    """One lineitem is one action token of its order; log-probabilities are formula stand-ins for volume, not model output."""
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount")
    b = -(1 + 10 * F.col("l_discount"))
    return table(spark, sf_dir, "lineitem").select(
        F.col("l_orderkey").alias("rollout_id"), (F.row_number().over(w) - 1).cast("long").alias("pos"), F.col("l_partkey").alias("token_id"), (F.col("l_returnflag") != "N").alias("mixed_action"),
        b.alias("b"), (b + (F.col("l_tax") - 0.04) * mismatch).alias("o"), (b + (F.col("l_tax") - 0.04) * mismatch + (F.col("l_quantity") - 25) / 100).alias("c"),
        F.col("l_suppkey").alias("node"), F.col("l_shipdate").alias("sampled_at"),
    ).withColumn("segment_seq", F.floor(F.col("pos") / 3)).withColumn("m", F.lit(1))


def lifecycle(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as rollouts: dispatched at ts, finished after value minutes, failed when the event is an error."""
    e = table(spark, sf_dir, "events")
    start = F.unix_micros(F.col("ts").cast("timestamp"))
    return e.select(
        F.col("event_id").alias("rollout_id"), F.floor(F.col("event_id") / SAMPLES).alias("group_id"), start.alias("dispatched"), (start + F.round(F.col("value") * 60e6).cast("long")).alias("finished"),
        (F.col("event_type") == "error").alias("failed"), F.col("user_id").alias("worker"), F.get_json_object("props", "$.k").cast("long").alias("payload"), F.col("value").alias("latency"),
    )
