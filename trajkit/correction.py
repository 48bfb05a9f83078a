"""Correction for the gap between the sampling policy and the actor.

b: log-probability recorded when a token was sampled; o: the actor's, recomputed before the update; c: the
current one. rho = exp(o - b). A weight w multiplies a token's loss; rejected tokens keep their place in the denominator.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from trajkit.registry import register

CAP, LOW, HIGH = 2.0, 0.5, 2.0


def rho():
    return F.exp(F.col("o") - F.col("b"))


def attach(trace: DataFrame) -> DataFrame:
    """Action tokens that lack their recorded log-probability or version: must be none."""
    return trace.filter((F.col("m") == 1) & (F.col("b").isNull() | F.isnan("b")))


@register("correction", "none")
def none(trace: DataFrame) -> DataFrame:
    return trace.withColumn("w", F.lit(1.0))


@register("correction", "token_truncate")
def token_truncate(trace: DataFrame, cap: float = CAP) -> DataFrame:
    return trace.withColumn("w", F.least(rho(), F.lit(cap)))


@register("correction", "token_mask")
def token_mask(trace: DataFrame, low: float = LOW, high: float = HIGH) -> DataFrame:
    return trace.withColumn("w", F.when(rho().between(low, high), rho()).otherwise(0.0))


def sequence_ratio(trace: DataFrame, agg: str = "geo", by: tuple[str, ...] = ("rollout_id", "segment_seq")) -> DataFrame:
    """log ratio of each sequence over its action tokens: the mean (geometric) or the sum (product)."""
    gap = F.when(F.col("m") == 1, F.col("o") - F.col("b"))
    w = Window.partitionBy(*by)
    return trace.withColumn("log_ratio", (F.avg(gap) if agg == "geo" else F.sum(gap)).over(w))


@register("correction", "seq_gate")
def seq_gate(trace: DataFrame, low: float = 0.99, high: float = 1.01, agg: str = "geo", by: tuple[str, ...] = ("rollout_id", "segment_seq")) -> DataFrame:
    """w is 1 in sequences whose ratio lies in [low, high] and 0 elsewhere."""
    return sequence_ratio(trace, agg, by).withColumn("w", F.exp("log_ratio").between(low, high).cast("double"))


@register("correction", "gate_truncate")
def gate_truncate(trace: DataFrame, low: float = 0.99, high: float = 1.01, cap: float = CAP, agg: str = "geo", by: tuple[str, ...] = ("rollout_id", "segment_seq")) -> DataFrame:
    """Whole sequences pass or fail; tokens of those that pass are weighted by their truncated ratio."""
    return seq_gate(trace, low, high, agg, by).withColumn("w", F.col("w") * F.least(rho(), F.lit(cap)))


@register("correction", "seq_truncate")
def seq_truncate(trace: DataFrame, cap: float = CAP, by: tuple[str, ...] = ("rollout_id",), check_versions: bool = True) -> DataFrame:
    """One weight for a whole sequence: its product ratio, truncated. Sequences that mix versions have no single sampling policy, so a trace that records versions is checked."""
    if check_versions and "version" in trace.columns and version_mix(trace, by).filter("n_versions > 1").limit(1).count():
        raise ValueError("a sequence mixes policy versions; use per-token rules")
    return sequence_ratio(trace, "prod", by).withColumn("w", F.least(F.exp("log_ratio"), F.lit(cap)))


def version_mix(trace: DataFrame, by: tuple[str, ...] = ("rollout_id",)) -> DataFrame:
    return trace.groupBy(*by).agg(F.countDistinct("version").alias("n_versions"), F.count("*").alias("n_tokens"))


def check(partial_rollout: bool, correction: str) -> None:
    """Partial rollout mixes versions inside a sequence, so it needs a correction that works per token."""
    if partial_rollout and correction in ("none", "seq_truncate"):
        raise ValueError("partial rollout requires a per-token importance correction")


def get_rule(name: str):
    from trajkit.registry import get

    return get("correction", name)
