"""Per-token loss contributions and their normalisation.

The window token mean divides one sum by one count over the whole optimizer window; ranks and microbatches only group
partial sums. Other normalisers are kept as baselines.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from trajkit.registry import register


def kl(kind: str, new: str = "o", ref: str = "ref") -> Column:
    d = F.col(new) - F.col(ref)
    return {"k1": d, "k2": 0.5 * d * d, "k3": F.exp(-d) - 1 + d}[kind]


def surrogate(kind: str = "clip", low: float = 0.2, high: float = 0.2, dual: float = 3.0, base: str = "actor") -> Column:
    """Loss of one token from q = exp(c - o) (or exp(c - b) with base "behaviour") and adv, without weights."""
    q = F.exp(F.col("c") - F.col("o" if base == "actor" else "b"))
    a = F.col("adv")
    plain, held = q * a, F.greatest(F.least(q, F.lit(1 + high)), F.lit(1 - low)) * a
    if kind == "plain":
        return -plain
    if kind == "clip":
        return -F.least(plain, held)
    if kind == "dual":
        return -F.when(a < 0, F.greatest(F.least(plain, held), dual * a)).otherwise(F.least(plain, held))
    raise ValueError(kind)


def contribution(loss: Column, beta: float = 0.0, eta: float = 0.0, kl_term: Column | None = None, entropy: Column | None = None) -> Column:
    """w * surrogate + beta * kl - eta * entropy; weights and rejections belong to the contribution, not to the denominator."""
    out = F.col("w") * loss
    if beta and kl_term is not None:
        out = out + beta * kl_term
    if eta and entropy is not None:
        out = out - eta * entropy
    return out


@register("loss", "window")
def window_token_mean(trace: DataFrame, value: str = "l") -> DataFrame:
    """num, den, loss: null where the window has no action token."""
    s = trace.agg(F.sum(F.col("m") * F.col(value)).alias("num"), F.sum("m").cast("long").alias("den"))
    return s.withColumn("loss", F.try_divide("num", "den"))


def partial_sums(trace: DataFrame, by: list[str], value: str = "l") -> DataFrame:
    return trace.groupBy(*by).agg(F.sum(F.col("m") * F.col(value)).alias("num"), F.sum("m").cast("long").alias("den"))


@register("loss", "mean_of_means")
def mean_of_means(trace: DataFrame, by: list[str], value: str = "l") -> DataFrame:
    """The mean over microbatches, sequences or ranks of their own token means: depends on how the window is cut."""
    return partial_sums(trace, by, value).filter("den > 0").agg(F.avg(F.col("num") / F.col("den")).alias("loss"))


@register("loss", "constant")
def constant_length(trace: DataFrame, length: int, value: str = "l") -> DataFrame:
    return trace.agg((F.sum(F.col("m") * F.col(value)) / (F.countDistinct("rollout_id") * F.lit(float(length)))).alias("loss"))


@register("loss", "accepted")
def accepted_only(trace: DataFrame, value: str = "l") -> DataFrame:
    """Divides by the tokens that the correction accepted: what the window token mean deliberately doesn't do."""
    return trace.agg(F.try_divide(F.sum(F.col("m") * F.col(value)), F.sum(F.col("m") * (F.col("w") > 0).cast("int"))).alias("loss"))


def invariance(trace: DataFrame, splits: list[tuple[int, int]], value: str = "l") -> DataFrame:
    """ranks, microbatches, loss, mean_of_means for several cuts of one window: the first must not move, the second does."""
    out = None
    for ranks, micro in splits:
        cut = trace.withColumn("_r", F.pmod("rollout_id", F.lit(ranks))).withColumn("_m", F.pmod(F.floor(F.col("rollout_id") / ranks), F.lit(micro)))
        p = partial_sums(cut, ["_r", "_m"], value)
        row = p.agg((F.sum("num") / F.sum("den")).alias("loss"), F.avg(F.try_divide("num", "den")).alias("mean_of_means")).select(F.lit(ranks).alias("ranks"), F.lit(micro).alias("microbatches"), "loss", "mean_of_means")
        out = row if out is None else out.unionByName(row)
    return out
